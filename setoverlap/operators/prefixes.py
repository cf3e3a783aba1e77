"""Exact similarity joins that write few bytes: sets are made again from their rows, not stored, and only keys travel.

1. One pass leaves each set's size and 128-bit digest, and from each partition its most frequent elements. Equal sets
   are one class; copies never meet.
2. A common order of elements puts the frequent ones last, by count, and all others by their hash. Two sets that
   similar share an element among the first n - ceil(n over / under) + 1 of each. Of these a 32-bit key and the group
   are shuffled once; a key of one group is dropped where it arrives, a key of many is dealt out in blocks.
3. Pairs are counted: the prefix that ends first holds all common elements up to its end, so a pair with c common keys
   has at most c + (what follows a prefix) common elements. Equal keys of different elements only add to c.
4. What can still be similar is compared on full sets, which are made for these groups alone.

The order changes cost, never the result: any order common to all sets gives the same pairs.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setoverlap.operators.skew import join_back, pairs_within
from setoverlap.session import materialised

#: Elements named by a partition, and in all: those that the common order puts last.
NAMED, LAST = 4_000, 50_000
#: A key of at most FEW groups is paired in its task; larger ones in blocks.
FEW = 64
#: Pairs held before they are added up, and elements counted at once.
HELD, COUNTED = 1_000_000, 4_000_000


def _arrays(batch):
    """group values and each row's array of 64-bit hashes."""
    col = batch.column(1)
    flat, ends = col.values.to_numpy(zero_copy_only=False), col.offsets.to_numpy()
    return batch.column(0), [flat[ends[i] : ends[i + 1]] for i in range(len(col))]


def summaries(sets: DataFrame) -> DataFrame:
    """g, n, d (digest) of each set (g long, h array of distinct hashes in order); rows without g name frequent elements
    (d null, e the element, n its sets)."""

    def run(batches):
        seen, parts, held = {}, [], 0

        def count():
            nonlocal parts, held
            e, c = np.unique(np.concatenate(parts), return_counts=True)
            keep = np.flatnonzero(c >= 2)
            for k, v in zip(e[keep].tolist(), c[keep].tolist(), strict=True):
                seen[k] = seen.get(k, 0) + v
            if len(seen) > 20 * NAMED:
                top = sorted(seen.items(), key=lambda x: (-x[1], x[0]))[: 10 * NAMED]
                seen.clear()
                seen.update(top)
            parts, held = [], 0

        schema = ["g", "n", "d", "e"]
        for batch in batches:
            g, hs = _arrays(batch)
            digests = [hashlib.blake2b(h.tobytes(), digest_size=16).hexdigest() for h in hs]
            for h in hs:
                parts.append(h)
                held += len(h)
                if held >= COUNTED:
                    count()
            n = len(hs)
            yield pa.RecordBatch.from_arrays([g, pa.array([len(h) for h in hs], pa.int64()), pa.array(digests, pa.string()), pa.nulls(n, pa.int64())], schema)
        if parts:
            count()
        top = sorted(seen.items(), key=lambda x: (-x[1], x[0]))[:NAMED]
        yield pa.RecordBatch.from_arrays([pa.nulls(len(top), pa.int64()), pa.array([c for _, c in top], pa.int64()), pa.nulls(len(top), pa.string()), pa.array([e for e, _ in top], pa.int64())], schema)

    return sets.mapInArrow(run, "g long, n long, d string, e long")


def prefix_keys(sets: DataFrame, last: np.ndarray, over: int, under: int) -> DataFrame:
    """(key, x): the prefix of each set under the common order; `last`: the frequent elements, rarest of them first."""
    order = np.argsort(last)
    known = last[order]

    def run(batches):
        for batch in batches:
            g, hs = _arrays(batch)
            keys, lengths = [], []
            for h in hs:
                size = len(h) - -(-len(h) * over // under) + 1
                at = np.minimum(np.searchsorted(known, h), max(len(known) - 1, 0))
                late = known[at] == h if len(known) else np.zeros(len(h), bool)
                p = h[~late][:size]
                if len(p) < size:
                    p = np.concatenate([p, last[np.sort(order[at[late]])[: size - len(p)]]])
                keys.append((p.view(np.uint64) >> np.uint64(32)).astype(np.uint32).view(np.int32))
                lengths.append(len(p))
            if keys:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), g.take(pa.array(np.repeat(np.arange(len(hs)), lengths)))], ["key", "x"])

    return sets.mapInArrow(run, "key int, x long")


def counted_pairs(rows: DataFrame) -> DataFrame:
    """(x, y, c), x < y: how many keys two groups share, of distinct (key, x); keys are shuffled once."""

    def run(batches):
        got = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if b.num_rows]
        schema = ["key", "x", "y", "c"]
        if not got:
            return
        key, x = (np.concatenate(v) for v in zip(*got, strict=True))
        del got
        order = np.lexsort((x, key))
        key, x = key[order], x[order]
        starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        sizes = np.diff(np.r_[starts, len(key)])
        for at, n in zip(starts[sizes > FEW], sizes[sizes > FEW], strict=True):
            yield pa.RecordBatch.from_arrays([pa.array(key[at : at + n].astype(np.int64)), pa.array(x[at : at + n]), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64())], schema)

        def added(parts):
            p, c = (np.concatenate(v) for v in zip(*parts, strict=True))
            u, back = np.unique(p, axis=0, return_inverse=True)
            return u, np.bincount(back.ravel(), c).astype(np.int64)

        parts, held = [], 0
        for n in range(2, FEW + 1):
            here = starts[sizes == n]
            a, b = np.triu_indices(n, 1)
            for k in range(0, len(here), max(1, HELD // len(a))):
                some = here[k : k + max(1, HELD // len(a))]
                p = np.stack([x[(some[:, None] + a).ravel()], x[(some[:, None] + b).ravel()]], 1)
                parts.append((p[p[:, 0] < p[:, 1]], np.ones(int((p[:, 0] < p[:, 1]).sum()))))
                held += len(p)
                if held > HELD:
                    parts = [added(parts)]
                    held = len(parts[0][0]) // 2
                    if held > HELD // 2:
                        (u, c), parts, held = parts[0], [], 0
                        yield pa.RecordBatch.from_arrays([pa.nulls(len(u), pa.int64()), pa.array(u[:, 0].copy()), pa.array(u[:, 1].copy()), pa.array(c)], schema)
        if parts:
            u, c = added(parts)
            yield pa.RecordBatch.from_arrays([pa.nulls(len(u), pa.int64()), pa.array(u[:, 0].copy()), pa.array(u[:, 1].copy()), pa.array(c)], schema)

    met = materialised(rows.repartition("key").mapInArrow(run, "key long, x long, y long, c long"))
    many = pairs_within(met.where("key is not null").select("key", "x"), ["key"], "x").groupBy("x", "y").agg(F.count("*").alias("c"))
    return met.where("key is null").select("x", "y", "c").unionByName(many).groupBy("x", "y").agg(F.sum("c").alias("c"))


def similar_pairs(rows: DataFrame, group: str, values: Column, over: int = 1, under: int = 2) -> DataFrame:
    """(x, y, card_both, card_any) with card_both / card_any >= over / under, exactly: between classes of equal sets, and
    (class, member) for each further member. rows: one a group (long, distinct); values: the set as an ordered array of
    distinct 64-bit hashes, made again in each pass."""
    sets = lambda r: r.select(F.col(group).cast("long").alias("g"), values.alias("h")).where("g is not null and size(h) > 0")
    all_ = materialised(summaries(sets(rows)))
    last = all_.where("d is null").groupBy("e").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "e").limit(LAST)
    last = np.array([r.e for r in last.collect()][::-1], np.int64)
    docs = all_.where("d is not null").select("g", "n", "d")
    first = docs.groupBy("d").agg(F.min("g").alias("class"), F.count("*").alias("k"))
    copies = materialised(join_back(docs, first, ["d"], "g", "k").where("g != class").select("class", "g", "n"))

    own = rows.join(copies.select(F.col("g").alias(group)), group, "left_anti")
    pairs = counted_pairs(prefix_keys(sets(own), last, over, under))
    n = lambda c: F.col(f"n{c}")
    rest = lambda c: F.ceil(n(c) * over / F.lit(under)) - 1
    sized = pairs.join(docs.select(F.col("g").alias("x"), F.col("n").alias("nx")), "x").join(docs.select(F.col("g").alias("y"), F.col("n").alias("ny")), "y")
    sized = sized.where(F.least("nx", "ny") * under >= F.greatest("nx", "ny") * over)
    near = materialised(sized.where((F.col("c") + F.greatest(rest("x"), rest("y"))) * (over + under) >= (n("x") + n("y")) * over).select("x", "y"))

    named = materialised(near.select(F.explode(F.array("x", "y")).alias(group)).distinct())
    full = materialised(sets(rows.join(named, group, "left_semi")))
    both = near.join(full.toDF("x", "hx"), "x").join(full.toDF("y", "hy"), "y")
    both = both.withColumn("card_both", F.size(F.array_intersect("hx", "hy")).cast("long")).withColumn("card_any", F.size("hx") + F.size("hy") - F.col("card_both"))
    same = copies.select(F.col("class").alias("x"), F.col("g").alias("y"), F.col("n").alias("card_both"), F.col("n").alias("card_any"))
    return both.where(F.col("card_both") * under >= F.col("card_any") * over).select("x", "y", "card_both", "card_any").unionByName(same)
