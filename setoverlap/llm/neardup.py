"""Near-duplicates by MinHash: universal hash minima, banding, verification, alternating large-star and small-star.

1. A document's words make its set of distinct five-word shingles (64-bit hashes); equal sets are one node, named by
   its smallest doc_id, so copies never become pairs.
2. BANDS x ROWS minima under universal hash functions make one key a band; a pair at similarity 0.75 shares no key
   with probability (1 - 0.75^ROWS)^BANDS, below 5e-5 at 0.75 itself and
   3e-8 at 0.8; long keys keep texts that share only a passage apart. Keys of one node only are dropped.
3. A star round joins each node with the smallest and the largest node that lead its keys; pairs pass an estimate
   from the minima, then the exact test on full sets. What then still shares a key across components is compared
   pair by pair in keys of few nodes; larger keys join into clusters whose nodes meet in blocks, as matrices.
4. Components come from alternating large-star and small-star steps over the links until nothing changes.

Defined cases: null or empty texts and texts without words have an empty set and link with nothing; with one to four
words the whole sequence is one shingle; repeated rows each get the same row; rows of one doc_id with different texts
share that node; a null doc_id is its own class (component null, kept); an empty table gives an empty result; other
columns are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setoverlap.llm.common import discard, id_and_text, materialised, small_batches

SHINGLE = 5
BANDS, ROWS, SEED = 96, 8, 11
#: Minima that the estimate before the exact test compares.
ESTIMATE = 128
SIMILAR = (75, 100)
#: Pairs whose share of equal minima falls below this cannot be similar (4.7 standard errors at 128 minima).
LEAST_ESTIMATE = 0.57
#: A key of at most FEW nodes is compared pair by pair; larger ones in blocks of about BLOCK nodes.
FEW, BLOCK = 16, 1024
#: A key with more than HOT_ROWS rows and at least one row in HOT_SHARE of all is dealt out over many tasks.
HOT_ROWS, HOT_SHARE = 64, 1000
MIX = np.uint64(0x9E3779B97F4A7C15)


def word_hashes(text: str, cache: dict[bytes, int]) -> np.ndarray:
    from xxhash import xxh3_64_intdigest

    words = text.encode("utf-8", "surrogatepass").lower().split()
    get, out = cache.get, []
    for w in words:
        h = get(w)
        if h is None:
            h = xxh3_64_intdigest(w)
            if len(cache) < 400_000 and len(w) < 40:
                cache[w] = h
        out.append(h)
    return np.array(out, np.uint64)


def shingle_set(text: str, cache: dict[bytes, int]) -> np.ndarray:
    """Sorted distinct hashes of the shingles."""
    h = word_hashes(text, cache)
    if not len(h):
        return h
    size = min(SHINGLE, len(h))
    out = np.full(len(h) - size + 1, size, np.uint64)
    with np.errstate(over="ignore"):
        for k in range(size):
            out = (out ^ h[k : len(h) - size + 1 + k]) * MIX
            out ^= out >> np.uint64(31)
    return np.unique(out)


def hash_family(n: int = BANDS * ROWS, seed: int = SEED) -> tuple[np.ndarray, np.ndarray]:
    """Multipliers (odd) and offsets of x -> high half of (a x + b) mod 2^64, a universal family."""
    r = np.random.default_rng(seed)
    return r.integers(1, 1 << 63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1), r.integers(0, 1 << 63, n, dtype=np.uint64)


def minima(shingles: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The smallest high half under each function, as 32-bit numbers; in blocks of shingles, so memory is bounded."""
    best = np.full(len(a), np.iinfo(np.uint64).max, np.uint64)
    with np.errstate(over="ignore"):
        for at in range(0, len(shingles), 256):
            x = shingles[at : at + 256]
            v = a[:, None] * x[None, :]
            v += b[:, None]
            np.minimum(best, v.min(1), out=best)
    return (best >> np.uint64(32)).astype(np.uint32)


def band_keys(m: np.ndarray) -> np.ndarray:
    rows = m.reshape(BANDS, ROWS).astype(np.uint64)
    out = np.arange(BANDS, dtype=np.uint64) + np.uint64(77)
    with np.errstate(over="ignore"):
        for k in range(ROWS):
            out = (out ^ rows[:, k]) * MIX
            out ^= out >> np.uint64(30)
    return out.view(np.int64)


def signatures(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, set_key (digest of the set; null when empty), keys (one a band)."""
    small_batches(docs.sparkSession)

    def run(batches):
        cache: dict[bytes, int] = {}
        a, b = hash_family()
        for batch in batches:
            n, digest, keys = [], [], []
            for text in batch.column(1).to_pylist():
                s = shingle_set(text, cache)
                n.append(len(s))
                digest.append(hashlib.blake2b(s.tobytes(), digest_size=16).hexdigest() if len(s) else None)
                keys.append(band_keys(minima(s, a, b)) if len(s) else np.zeros(0, np.int64))
            offsets = np.cumsum([0, *map(len, keys)]).astype(np.int32)
            flat = np.concatenate(keys) if keys else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(digest, pa.string()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], ["doc_id", "n_shingles", "set_key", "keys"])

    return id_and_text(docs).mapInArrow(run, "doc_id long, n_shingles long, set_key string, keys array<long>")


def full_sets(texts: DataFrame) -> DataFrame:
    """node, minima (binary), shingles (binary) for rows (doc_id, text)."""
    small_batches(texts.sparkSession)

    def run(batches):
        cache: dict[bytes, int] = {}
        a, b = (x[:ESTIMATE] for x in hash_family())
        for batch in batches:
            sets = [shingle_set(t, cache) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([minima(s, a, b).tobytes() for s in sets], pa.binary()), pa.array([s.tobytes() for s in sets], pa.binary())], ["node", "minima", "shingles"])

    return texts.mapInArrow(run, "node long, minima binary, shingles binary")


def verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (u, v) that pass the estimate and the exact test on full sets."""

    def side(name: str) -> DataFrame:
        return sets.select(F.col("node").alias(name), F.struct("minima", "shingles").alias(f"{name}_set"))

    both = pairs.join(side("u"), "u").join(side("v"), "v").select("u", "v", "u_set", "v_set")
    over, under = SIMILAR

    def run(batches):
        for batch in batches:
            us, vs = batch.column(2), batch.column(3)
            keep = []
            for i in range(batch.num_rows):
                x, y = us[i].as_py(), vs[i].as_py()
                if np.mean(np.frombuffer(x["minima"], np.uint32) == np.frombuffer(y["minima"], np.uint32)) < LEAST_ESTIMATE:
                    keep.append(False)
                    continue
                s, t = np.frombuffer(x["shingles"], np.uint64), np.frombuffer(y["shingles"], np.uint64)
                common = len(np.intersect1d(s, t, assume_unique=True))
                keep.append(under * common >= over * (len(s) + len(t) - common))
            mask = pa.array(keep, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(mask), batch.column(1).filter(mask)], ["u", "v"])

    return both.mapInArrow(run, "u long, v long")


def within_clusters(nodes: DataFrame, sets: DataFrame) -> DataFrame:
    """Links (u, v) between components of one cluster, enough of them to join what is linked.

    nodes: (node, cluster, component). A cluster is dealt into blocks of about BLOCK nodes; each two blocks meet in one
    task, which compares their minima as matrices and the near ones by full sets, and returns a link only
    where it joins two components of the task. Rows grow as n^2 / BLOCK; no pair is written out.
    """
    small_batches(sets.sparkSession)
    sizes = nodes.groupBy("cluster").agg(F.count("*").alias("n"), F.min("component").alias("c1"), F.max("component").alias("c2")).where("c1 < c2")
    rows = nodes.join(sizes.select("cluster", F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks")), "cluster").join(sets, "node")
    mine = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
    rows = rows.withColumn("mine", mine).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.select("cluster", F.least("mine", "j").alias("i"), F.greatest("mine", "j").alias("j"), "mine", "node", "component", "minima", "shingles")
    over, under = SIMILAR

    def compare(frame):
        import pandas as pd

        i, j = frame["i"].iloc[0], frame["j"].iloc[0]
        root: dict[int, int] = {}

        def find(c: int) -> int:
            while root.get(c, c) != c:
                c = root[c]
            return c

        x, y = (frame[frame["mine"] == k].drop_duplicates("node") for k in (i, j))
        out = []
        if len(x) and len(y):
            mx, my = (np.stack([np.frombuffer(m, np.uint32) for m in f["minima"]]) for f in (x, y))
            cx, cy = x["component"].to_numpy(), y["component"].to_numpy()
            sx, sy = ([np.frombuffer(b, np.uint64) for b in f["shingles"]] for f in (x, y))
            nx, ny = x["node"].to_numpy(), y["node"].to_numpy()
            for p in range(len(x)):
                near = np.flatnonzero(((my == mx[p]).mean(1) >= LEAST_ESTIMATE) & (cy != cx[p]))
                for q in near:
                    a, b = find(int(cx[p])), find(int(cy[q]))
                    if a == b:
                        continue
                    common = len(np.intersect1d(sx[p], sy[q], assume_unique=True))
                    if under * common >= over * (len(sx[p]) + len(sy[q]) - common):
                        root[max(a, b)] = min(a, b)
                        out.append((int(min(nx[p], ny[q])), int(max(nx[p], ny[q]))))
        return pd.DataFrame(out, columns=["u", "v"]).astype("int64")

    return rows.groupBy("cluster", "i", "j").applyInPandas(compare, "u long, v long")


def join_back(rows: DataFrame, stats: DataFrame, key: str, other: str) -> DataFrame:
    """rows joined with the statistics of their key (one row a key, with its row count n), hot keys dealt out.

    A key is hot when it has a HOT_SHARE of all rows, so at most HOT_SHARE keys are hot: their list is broadcast, their
    rows are dealt by `other` over as many salts as there are shuffle partitions, and only their statistics are copied.
    """
    spark = rows.sparkSession
    salts = max(2, min(4096, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    total = stats.agg(F.sum("n")).first()[0] or 0
    hot = F.broadcast(stats.where((F.col("n") > HOT_ROWS) & (F.col("n") * HOT_SHARE >= total)).select(key, F.lit(True).alias("hot")))
    dealt = rows.join(hot, key, "left").withColumn("salt", F.when(F.col("hot"), F.pmod(F.xxhash64(other), F.lit(salts)).cast("int")).otherwise(0)).drop("hot")
    copies = F.when(F.col("hot"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0)))
    return dealt.join(stats.join(hot, key, "left").withColumn("salt", F.explode(copies)).drop("hot"), [key, "salt"]).drop("salt")


def with_least(edges: DataFrame, cap: bool) -> DataFrame:
    """edges (u, v) with m, the least v of each u (and u itself where `cap`).

    A hub's edges are dealt by v over as many salts as there are shuffle partitions: minima are taken for each
    (u, salt), then for each u, and go back to the salts that u has, so no task reads a hub's edges whole.
    """
    salts = max(2, min(4096, int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    dealt = edges.withColumn("s", F.pmod(F.xxhash64("v"), F.lit(salts)).cast("int"))
    part = dealt.groupBy("u", "s").agg(F.min("v").alias("m"))
    whole = part.groupBy("u").agg(F.min("m").alias("m"), F.collect_set("s").alias("s"))
    least = F.least("m", "u") if cap else F.col("m")
    return dealt.join(whole.select("u", least.alias("m"), F.explode("s").alias("s")), ["u", "s"]).select("u", "v", "m")


def components(links: DataFrame) -> DataFrame:
    """node, component (its smallest node) for the nodes of undirected links (u, v): alternating star steps.

    Tables between steps are written to the shared folder and deleted once the next step stands.
    """
    edges = materialised(links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u > v").distinct())
    before = None
    while True:
        # large star: larger neighbours of u hang from the least of u and its neighbours
        ways = with_least(edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))), True)
        large = ways.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").distinct()
        # small star: u and its smaller neighbours hang from the least of these
        hung = with_least(large, False).select(F.explode(F.array("u", "v")).alias("u"), F.col("m").alias("v"))
        old, edges = edges, materialised(hung.where("u > v").distinct())
        discard(old)
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    roots = edges.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots).distinct()


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id, kept: one row a document."""
    signed = materialised(signatures(docs))
    nodes = signed.where("set_key is not null and doc_id is not null").groupBy("set_key").agg(F.min("doc_id").alias("node"))
    nodes = materialised(nodes)
    heads = signed.join(nodes, "set_key").where("doc_id = node").select("node", "keys").dropDuplicates(["node", "keys"])
    keyed = heads.select("node", F.explode("keys").alias("key"))
    shared = materialised(keyed.groupBy("key").agg(F.min("node").alias("low"), F.max("node").alias("high"), F.count("*").alias("n")).where("low < high"))
    buckets = materialised(join_back(keyed, shared, "key", "node"))

    texts = id_and_text(docs).join(buckets.select(F.col("node").alias("doc_id")).distinct(), "doc_id").dropDuplicates(["doc_id", "text"])
    sets = materialised(full_sets(texts.select("doc_id", "text")))

    members = buckets.select("node").distinct()
    near = buckets.groupBy("node").agg(*[f(F.when(F.col(c) != F.col("node"), F.col(c))).alias(n) for n, f, c in (("u1", F.min, "low"), ("u2", F.max, "high"))])
    star = near.select("node", F.explode(F.array_distinct(F.filter(F.array("u1", "u2"), lambda x: x.isNotNull()))).alias("u"))
    star = materialised(star.select(F.least("u", "node").alias("u"), F.greatest("u", "node").alias("v")).distinct())
    links = materialised(verified(star, sets))
    first = materialised(members.join(components(links), "node", "left").select("node", F.coalesce("component", "node").alias("component")))

    # what still crosses components: keys of few nodes pair by pair, keys of many inside blocks of their cluster
    hubs = materialised(buckets.where(F.col("n") > FEW).select(F.col("low").alias("u"), F.col("node").alias("v")).distinct())
    clusters = materialised(components(hubs).select("node", F.col("component").alias("cluster")))
    placed = buckets.where(F.col("n") <= FEW).select("key", "node").join(first, "node").join(clusters, "node", "left")
    open_ = materialised(placed.select("key", "node", "component", F.coalesce("cluster", -F.col("node") - 1).alias("cluster")))
    other = open_.toDF("key", "v", "v_component", "v_cluster")
    pairs = open_.toDF("key", "u", "u_component", "u_cluster").join(other, "key").where("u < v and u_component != v_component and u_cluster != v_cluster")
    pairs = materialised(pairs.select("u", "v").distinct().join(star, ["u", "v"], "left_anti"))
    more, blocks = materialised(verified(pairs, sets)), materialised(within_clusters(clusters.join(first, "node"), sets))
    joined = links.unionByName(more).unionByName(blocks)
    labels = materialised(members.join(components(joined), "node", "left").select("node", F.coalesce("component", "node").alias("component")))
    discard(shared, buckets, sets, star, links, first, hubs, clusters, open_, pairs, more, blocks)

    named = nodes.join(labels, "node", "left").select("set_key", F.coalesce("component", "node").alias("component"))
    out = signed.select("doc_id", "n_shingles", "set_key").join(named, "set_key", "left")
    component = F.coalesce("component", "doc_id")
    component = F.when(F.col("doc_id").isNull(), F.lit(None).cast("long")).otherwise(component)
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def keep_first(docs: DataFrame) -> DataFrame:
    """The rows of docs, all columns, that their class keeps: those of the class's smallest doc_id, repeated rows once
    (rows that share this doc_id but not the text all stay), and rows without a doc_id."""
    names = docs.columns
    kept = near_duplicates(docs).where("kept and doc_id is not null").select(F.col("doc_id").alias("n_id")).distinct()
    text = F.md5(F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary"))
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("n_row"), F.col("doc_id").cast("long").alias("n_id"), text.alias("n_text"))
    stay = rows.join(kept, "n_id", "left_semi").dropDuplicates(["n_id", "n_text"])
    return stay.unionByName(rows.where(F.col("n_id").isNull())).select(*[F.col(f"n_row.`{c}`").alias(c) for c in names])


ORACLE = r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + 4], ' ') AS g FROM d, unnest(range(1, greatest(len(w) - 3, 2))) AS u(i) WHERE len(w) > 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS (SELECT u, v FROM p JOIN n x ON p.u = x.doc_id JOIN n y ON p.v = y.doc_id WHERE 100 * c >= 75 * (x.n + y.n - c)),
r AS (SELECT doc_id AS s, doc_id AS t FROM d UNION SELECT r.s, e.v FROM r JOIN e ON r.t = e.u),
m AS (SELECT s, min(t) AS c FROM r GROUP BY s)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, m.c AS component_id, d.doc_id = m.c AS kept
FROM d LEFT JOIN n ON d.doc_id = n.doc_id JOIN m ON d.doc_id = m.s
"""
