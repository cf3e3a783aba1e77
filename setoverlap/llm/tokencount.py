"""Token counts for a SentencePiece BPE model by a two-tier lookup, map side only.

No piece of such a model holds a word mark after another character, so merges never cross a word's head and a
text's count is the sum over its pre-tokens (a run of marks with the characters up to the next mark). Tier one is
a broadcast table of the lengths of the corpus's frequent pre-tokens: a first pass over all texts keeps in each partition
the SUMMARY pre-tokens seen most (counts pruned batch by batch, so memory is bounded), the summaries are added up, and
the FREQUENT highest are encoded once. The table changes speed, never a count. Misses are encoded by the library and
kept in a bounded cache of the worker. No pre-token of a text is shuffled: only partitions' summaries are.

Defined cases: null text counts as empty (0 bytes, 0 tokens); repeated rows each get a row; an empty table gives
an empty result; other columns are not read; a text without blanks is one pre-token, whatever its length.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setoverlap.llm.common import id_and_text, small_batches

MARK = "▁"
CACHE_ROWS = 500_000
CACHE_CHARS = 64
LIMIT = 4096
#: Pre-tokens that a partition's summary holds, that the broadcast table holds, and their longest length.
SUMMARY, FREQUENT, FREQUENT_CHARS = 4_000, 50_000, 32


def _processor(model: bytes):
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_proto=model)


def checked(sp) -> None:
    """Counts add up over pre-tokens only if no piece crosses a word's head."""
    if any(MARK in sp.id_to_piece(i).lstrip(MARK) for i in range(sp.get_piece_size())):
        raise ValueError("the model has pieces across words; counts do not add up over pre-tokens")


def partition_summary(batches, size: int = SUMMARY) -> Iterator[pa.RecordBatch]:
    """The `size` pre-tokens that these texts hold most, with counts; never more than 8 * size are kept between batches."""
    seen: Counter = Counter()
    for batch in batches:
        for text in batch.column(1).to_pylist():
            seen.update(units_of(text))
        if len(seen) > 8 * size:
            seen = Counter(dict(seen.most_common(4 * size)))
    top = [(u, n) for u, n in seen.most_common(size) if n > 1 and len(u) <= FREQUENT_CHARS]
    yield pa.RecordBatch.from_arrays([pa.array([u for u, _ in top], pa.string()), pa.array([n for _, n in top], pa.int64())], ["unit", "n"])


def frequent_units(df: DataFrame, limit: int = FREQUENT) -> list[str]:
    """The pre-tokens (without their first mark) that the partitions' summaries count most, at most `limit`."""
    small_batches(df.sparkSession)
    found = id_and_text(df).mapInArrow(partition_summary, "unit string, n long").groupBy("unit").agg(F.sum("n").alias("n"))
    return [r["unit"] for r in found.orderBy(F.desc("n"), "unit").limit(limit).collect()]


def lengths_of(model: bytes, units: list[str]) -> dict[str, int]:
    """Tokens of each of these pre-tokens; the mark alone, which the library cannot be given as a word, is always there."""
    sp = _processor(model)
    checked(sp)
    alone = {"": len(sp.encode(MARK)) if sp.piece_to_id(MARK * 2) == sp.unk_id() else 1}
    return (dict(zip(units, map(len, sp.encode(units, num_threads=1)), strict=True)) if units else {}) | alone


class Lengths:
    """Broadcast table in front, the library behind; `cache` holds what was encoded, up to a bound."""

    def __init__(self, table: dict[str, int], sp):
        self.table, self.sp, self.cache = table, sp, {}

    def add(self, texts: list[list[str]]) -> dict[str, int]:
        """Lengths of all units of these texts; units missing in both tiers are encoded in one call."""
        units = set().union(*texts)
        missing = [u for u in units if u not in self.cache and u not in self.table]
        found = dict(zip(missing, map(len, self.sp.encode(missing, num_threads=1)), strict=True)) if missing else {}
        if len(self.cache) + len(found) > CACHE_ROWS:
            known = {u: self.cache[u] for u in units if u in self.cache}
            self.cache.clear()
            found |= known
        self.cache.update((u, n) for u, n in found.items() if len(u) <= CACHE_CHARS)
        return found


def units_of(text: str) -> list[str]:
    """Pre-tokens without their first mark; a run of marks belongs to the word after it."""
    if not text:
        return []
    marked = text.replace(" ", MARK)
    if MARK * 2 in marked or marked[0] == MARK or marked[-1] == MARK:
        return [u[1:] for u in re.findall(f"{MARK}+[^{MARK}]*", MARK + marked)]
    return marked.split(MARK)


def counts(texts: list[str], lengths: Lengths) -> list[int]:
    split = [units_of(t) for t in texts]
    found, table, cache = lengths.add(split), lengths.table, lengths.cache
    get = {u: n for u, n in found.items() if u not in cache}
    out = []
    for units in split:
        total = 0
        for u in units:
            n = table.get(u)
            if n is None:
                n = cache.get(u)
                if n is None:
                    n = get[u]
            total += n
        out.append(total)
    return out


_WORKER: dict[bytes, Lengths] = {}


def worker_lengths(model: bytes, table: dict[str, int]) -> Lengths:
    """One cache for all tasks of a worker and model."""
    key = hashlib.sha256(model).digest() + len(table).to_bytes(8, "big")
    if key not in _WORKER:
        _WORKER.clear()
        _WORKER[key] = Lengths(table, _processor(model))
    return _WORKER[key]


def token_counts(df: DataFrame, model_path: str, limit: int = LIMIT, frequent: list[str] | None = None) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit; `frequent` spares the first pass where the pre-tokens are known."""
    with open(model_path, "rb") as f:
        model = f.read()
    units = frequent_units(df) if frequent is None else frequent
    shared = df.sparkSession.sparkContext.broadcast((model, lengths_of(model, units)))

    def run(batches):
        lengths = worker_lengths(*shared.value)
        for batch in batches:
            texts = batch.column(1).to_pylist()
            n = counts(texts, lengths)
            size = [len(t.encode("utf-8", "surrogatepass")) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size, pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    small_batches(df.sparkSession)
    return id_and_text(df).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
