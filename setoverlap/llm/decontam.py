"""Benchmark decontamination by template canonicalisation.

Words become template tokens: numbers, units and names (capitalised words that are no function words, wherever they
stand) turn into typed placeholders, a run of names or of numbers (number words too) within a sentence into one,
other words into their lower-case letters. Hashed windows of all documents meet those of the benchmark in a hash join;
a window has LEAST_WINDOW to WINDOW tokens, fewer for short items (`window_of`), so that an item survives a changed
token, and documents emit windows of every length in use. Windows of one (document, item) pair whose relative positions
lie within MAX_SHIFT tokens of each other are gathered as one passage; each item token takes its partner from the
position with the most windows; slot values are compared, and passages that cover enough of the item's tokens are
reported. A re-parameterised copy keeps the template while its slots change; it is consistent when equal item values map
to equal document values. An item of fewer than LEAST_WINDOW tokens is one window and must keep its own slot values.

The benchmark side is broadcast only while its measured bytes are within BROADCAST_BYTES. Beyond that the documents'
hashes alone meet the benchmark's in a shuffled semi-join, and only texts that hold a hit are read again for their slots.

Defined cases: null and blank texts hold nothing, as document or item; a text with fewer tokens than a window has no such
window; a null doc_id is reported as null; documents are told apart by doc_id and text, so rows that share an id but
not a text are judged one by one and repeated rows once; start is the document's word where the item would begin;
empty tables give an empty result; other columns are not read.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from setoverlap.llm.common import materialised, small_batches

WINDOW = 8
LEAST_WINDOW = 4
#: Positions of one passage may drift by so many tokens from one to the next (words inserted or dropped).
MAX_SHIFT = 4
LEAST_COVER = 0.6
#: Most bytes of benchmark windows (hashes, places and slot values) that are sent to every worker.
BROADCAST_BYTES = 64 << 20
EDGE = ".,;:!?\"'()[]{}*%$&#|<>"
NUMBER = re.compile(r"[+-]?[0-9][0-9.,:/]*")
# Units of measure and money; words for numbers; words that start sentences without being names.
UNITS = frozenset("mm cm m km kg g mg l ml lb lbs oz ft inch inches mile miles meter meters metre metres hour hours minute minutes second seconds day days week weeks month months year years dollar dollars euro euros cent cents percent degrees usd eur".split())
NUMBER_WORDS = frozenset("zero one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty thirty forty fifty sixty seventy eighty ninety hundred thousand million billion".split())
FUNCTION_WORDS = frozenset("the a an and or but if in on at to of for from by with as it its he she they we you his her their this that these those there here what which who when where why how is are was were do does did can could will would has have had not no each every all some any then so after before while der die das ein eine und oder wenn in im am an auf zu von mit für es er sie wir wie was wer wo ist sind war hat nicht el la los las un una y o si en de del por con para que se le les des du et ou dans il elle ils est sont".split())
NUM, UNIT, NAME = "<num>", "<unit>", "<name>"


class Canonical:
    """Template tokens of texts as 64-bit hashes; distinct words are looked up once per worker task."""

    def __init__(self, cap: int = 300_000):
        self.cap, self.known, self.name, self.num, self.unit = cap, {}, self._hash(NAME), self._hash(NUM), self._hash(UNIT)

    @staticmethod
    def _hash(s: str) -> int:
        import xxhash

        return xxhash.xxh3_64_intdigest(s.encode("utf-8", "surrogatepass"))

    def _look(self, raw: str) -> tuple[int, int]:
        """Hash of the token and flags: 2 ends a sentence, 4 is a slot."""
        w = raw.strip(EDGE)
        ends = 2 * raw.rstrip("\"')]}*%$&#|").endswith((".", "!", "?"))
        low = w.lower()
        if NUMBER.fullmatch(w) or (low in NUMBER_WORDS or ("-" in low and NUMBER_WORDS.issuperset(low.split("-")))):
            out = (self.num, ends | 4)
        elif low in UNITS:
            out = (self.unit, ends | 4)
        elif w[:1] != w[:1].lower() and w != w.upper() and low not in FUNCTION_WORDS:
            out = (self.name, ends | 4)
        else:
            out = (self._hash(low), ends)
        if len(raw) < 40:
            if len(self.known) >= self.cap:
                self.known.clear()
            self.known[raw] = out
        return out

    def tokens(self, text: str) -> tuple[np.ndarray, list[str], np.ndarray, np.ndarray]:
        """Hashes, words (a run's words joined), which tokens are slots, and each token's first word."""
        words = text.split()
        get, look = self.known.get, self._look
        found = [get(w) or look(w) for w in words]
        flags = np.fromiter((f for _, f in found), np.int8, len(found))
        h = np.fromiter((x for x, _ in found), np.uint64, len(found))
        slot = (flags & 4) > 0
        joined = np.zeros(len(h), bool)
        if len(h):
            joined[1:] = ((flags[:-1] & 2) == 0) & (h[1:] == h[:-1]) & ((h[1:] == self.name) | (h[1:] == self.num))
        first = np.flatnonzero(~joined)
        if len(first) == len(h):
            return h, words, slot, first
        ends = np.append(first[1:], len(h))
        words = [words[a] if b - a == 1 else " ".join(w.strip(EDGE) for w in words[a:b]) for a, b in zip(first.tolist(), ends.tolist(), strict=True)]
        return h[first], words, slot[first], first


def window_of(n: int) -> int:
    """Window length for an item of n tokens: with one token changed, 0.6 of 10 tokens or more stay within whole windows."""
    return min(n, max(LEAST_WINDOW, min(WINDOW, n * 2 // 5)))


def windows(h: np.ndarray, sizes: list[int]) -> dict[int, np.ndarray]:
    """One 64-bit hash for each window of each length; a length above the text's has none."""
    found, top = {}, max(sizes, default=0)
    out = np.full(len(h), 1469598103934665603, np.uint64)
    with np.errstate(over="ignore"):
        for k in range(min(top, len(h))):
            out = (out[: len(h) - k] ^ h[k:]) * np.uint64(0x9E3779B97F4A7C15)
            out ^= out >> np.uint64(29)
            if k + 1 in sizes:
                x = (out ^ np.uint64(k + 1)) * np.uint64(0xBF58476D1CE4E5B9)
                found[k + 1] = x ^ (x >> np.uint64(31))
    return found


def _slots(words: list[str], slot: np.ndarray, start: int, size: int) -> list[str]:
    return [words[i].strip(EDGE) if slot[i] else "" for i in range(start, min(start + size, len(words)))]


def benchmark_windows(benchmark: DataFrame) -> DataFrame:
    """item_id, n_tokens, size, pos, pos_word, hash, item_slots (of the window's tokens; empty where there is none)."""
    small_batches(benchmark.sparkSession)

    def run(batches):
        can = Canonical()
        for batch in batches:
            rows = []
            for i, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                h, words, slot, first = can.tokens(text)
                if len(h):
                    size = window_of(len(h))
                    rows += [(i, len(h), size, p, int(first[p]), int(x), _slots(words, slot, p, size)) for p, x in enumerate(windows(h, [size])[size].view(np.int64))]
            cols = list(zip(*rows, strict=True)) if rows else [()] * 7
            kinds = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.list_(pa.string())]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["item_id", "n_tokens", "size", "pos", "pos_word", "hash", "item_slots"])

    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return items.mapInArrow(run, "item_id long, n_tokens int, size int, pos int, pos_word int, hash long, item_slots array<string>")


def _texts(docs: DataFrame) -> DataFrame:
    """doc_id, d_key (digest of the text), text."""
    t = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), _digest(t).alias("d_key"), t.alias("text"))


def _digest(text):
    return F.md5(text.cast("binary"))


def document_hits(texts: DataFrame, sizes: list[int], only: "object") -> DataFrame:
    """doc_id, d_key, at, at_word, hash, doc_slots of the windows whose hash the broadcast sorted array `only` holds."""
    small_batches(texts.sparkSession)

    def run(batches):
        can, wanted = Canonical(), only.value
        for batch in batches:
            row, at, at_word, hashes, slots = [], [], [], [], []
            for r, text in enumerate(batch.column(2).to_pylist()):
                h, words, slot, first = can.tokens(text)
                for size, x in windows(h, sizes).items():
                    w = x.view(np.int64)
                    near = np.minimum(np.searchsorted(wanted, w), max(0, len(wanted) - 1))
                    keep = np.flatnonzero(wanted[near] == w) if len(wanted) else np.zeros(0, np.int64)
                    row += [r] * len(keep)
                    at += keep.tolist()
                    at_word += first[keep].tolist()
                    hashes += w[keep].tolist()
                    slots += [_slots(words, slot, p, size) for p in keep.tolist()]
            of = pa.array(row, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(of), batch.column(1).take(of), pa.array(at, pa.int32()), pa.array(at_word, pa.int32()), pa.array(hashes, pa.int64()), pa.array(slots, pa.list_(pa.string()))], ["doc_id", "d_key", "at", "at_word", "hash", "doc_slots"])

    return texts.mapInArrow(run, "doc_id long, d_key string, at int, at_word int, hash long, doc_slots array<string>")


def shuffled_hits(texts: DataFrame, sizes: list[int], bench: DataFrame) -> DataFrame:
    """The same for a benchmark of any size: hashes meet in a semi-join, then the texts with hits give their slots."""
    small_batches(texts.sparkSession)

    def hashes(batches):
        can = Canonical()
        for batch in batches:
            row, found = [], []
            for r, text in enumerate(batch.column(2).to_pylist()):
                for x in windows(can.tokens(text)[0], sizes).values():
                    distinct = np.unique(x.view(np.int64))
                    row += [r] * len(distinct)
                    found.append(distinct)
            flat = np.concatenate(found) if found else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(1).take(pa.array(row, pa.int64())), pa.array(flat, pa.int64())], ["d_key", "hash"])

    def places(batches):
        can = Canonical()
        for batch in batches:
            row, at, at_word, out, slots = [], [], [], [], []
            for r, (text, wanted) in enumerate(zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)):
                h, words, slot, first = can.tokens(text)
                for size, x in windows(h, sizes).items():
                    w = x.view(np.int64)
                    for p in np.flatnonzero(np.isin(w, np.array(wanted, np.int64))).tolist():
                        row.append(r)
                        at.append(p)
                        at_word.append(int(first[p]))
                        out.append(int(w[p]))
                        slots.append(_slots(words, slot, p, size))
            of = pa.array(row, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(of), batch.column(1).take(of), pa.array(at, pa.int32()), pa.array(at_word, pa.int32()), pa.array(out, pa.int64()), pa.array(slots, pa.list_(pa.string()))], ["doc_id", "d_key", "at", "at_word", "hash", "doc_slots"])

    met = texts.mapInArrow(hashes, "d_key string, hash long").join(bench.select("hash").distinct(), "hash", "left_semi")
    wanted = met.groupBy("d_key").agg(F.collect_set("hash").alias("wanted"))
    return texts.join(wanted, "d_key").select("doc_id", "d_key", "text", "wanted").mapInArrow(places, "doc_id long, d_key string, at int, at_word int, hash long, doc_slots array<string>")


def passages(texts: DataFrame, benchmark: DataFrame, least_cover: float = LEAST_COVER, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """doc_id, d_key, item_id, start, n_windows, cover, n_slots, n_changed_slots, consistent of each reported passage."""
    spark = texts.sparkSession
    bench = materialised(benchmark_windows(benchmark))
    slot_bytes = F.coalesce(F.aggregate("item_slots", F.lit(0).cast("long"), lambda n, x: n + F.octet_length(x) + 8), F.lit(0))
    measured = bench.agg(F.sum(slot_bytes + 40).alias("bytes"), F.collect_set("size").alias("sizes")).first()
    sizes = sorted(measured["sizes"])
    if (measured["bytes"] or 0) <= broadcast_bytes:
        hashes = np.unique(np.array([r["hash"] for r in bench.select("hash").distinct().collect()], np.int64))
        hits = document_hits(texts, sizes, spark.sparkContext.broadcast(hashes)).join(F.broadcast(bench), "hash")
    else:
        hits = shuffled_hits(texts, sizes, bench).join(bench, "hash")
    hits = hits.withColumn("line", F.col("at") - F.col("pos"))
    # windows on one line of relative position: (item token, item value, document value) without repeats
    tokens = F.zip_with("item_slots", "doc_slots", lambda a, b: F.struct(a.alias("a"), b.alias("b")))
    placed = F.transform(tokens, lambda x, i: F.struct((F.col("pos") + i).alias("t"), x["a"].alias("a"), x["b"].alias("b")))
    pair = ["doc_id", "d_key", "item_id"]
    lines = hits.groupBy(*pair, "line").agg(
        F.collect_set("pos").alias("at_pos"), F.first("n_tokens").alias("n_tokens"), F.min_by(F.col("at_word") - F.col("pos_word"), F.col("pos")).alias("start"),
        F.array_distinct(F.flatten(F.collect_set(placed))).alias("tokens"),
    )
    # lines close to each other are one passage
    order = Window.partitionBy(*pair).orderBy("line")
    apart = F.coalesce(F.col("line") - F.lag("line").over(order) > MAX_SHIFT, F.lit(False))
    lines = lines.withColumn("apart", apart.cast("int")).withColumn("passage", F.sum("apart").over(order))
    key = [*pair, "passage"]
    # each item token once, from the line with the most windows; the line with the first window gives the start
    strong = F.struct(-F.size("at_pos"), F.col("line"))
    ranked = lines.withColumn("strong", strong).select(*key, "n_tokens", "start", "at_pos", "strong", F.explode("tokens").alias("x"))
    best = ranked.groupBy(*key, F.col("x.t").alias("t")).agg(
        F.first("n_tokens").alias("n_tokens"), F.min(F.struct("strong", "x.a", "x.b")).alias("best"), F.min_by("start", "strong").alias("start"), F.max(F.expr("array_contains(at_pos, x.t)").cast("int")).alias("begins"),
    )
    slot = F.when((F.col("best.a") != "") | (F.col("best.b") != ""), F.struct("best.a", "best.b"))
    got = best.groupBy(*key).agg(
        F.sum("begins").alias("n_windows"), F.count("*").alias("covered"), F.first("n_tokens").alias("n_tokens"), F.min_by("start", "t").alias("start"), F.collect_set(slot).alias("slots"),
    )
    cover = F.col("covered") / F.col("n_tokens")
    consistent = F.size("slots") == F.size(F.array_distinct(F.transform("slots", lambda x: x["a"])))
    out = got.select(
        *pair, "start", F.col("n_windows").cast("long").alias("n_windows"), cover.alias("cover"), F.size("slots").cast("long").alias("n_slots"),
        F.size(F.filter("slots", lambda x: x["a"] != x["b"])).cast("long").alias("n_changed_slots"), consistent.alias("consistent"), (F.col("n_tokens") >= LEAST_WINDOW).alias("template"),
    )
    fits = F.when(F.col("template"), F.col("consistent") | (F.col("n_changed_slots") * 2 <= F.col("n_slots"))).otherwise(F.col("n_changed_slots") == 0)
    return out.where((F.col("cover") >= least_cover) & fits).drop("template")


def contaminated(docs: DataFrame, benchmark: DataFrame, least_cover: float = LEAST_COVER, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """doc_id, item_id, start, n_windows, cover, n_slots, n_changed_slots, consistent: one row for each reported passage."""
    return passages(_texts(docs), benchmark, least_cover, broadcast_bytes).drop("d_key")


def decontaminate(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of docs, all columns, whose text holds no benchmark passage; any doc_id, null too."""
    names = docs.columns
    bad = passages(_texts(docs), benchmark).select("d_key").distinct()
    kept = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("d_row"), _digest(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("d_key"))
    return kept.join(bad, "d_key", "left_anti").select(*[F.col(f"d_row.`{c}`").alias(c) for c in names])
