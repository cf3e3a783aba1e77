"""Six sums of a pair of sketches; every estimator, likelihood and bound needs only these.

k_tie: registers that tie; k_b: B's private part won (A's maximum is smaller); k_a: A's private part won;
sum_a, sum_b, sum_any: energies of A, B and their union. Bucketed sketches add k_none and the counts of winners
where the other side was seen.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setoverlap.functions.hashing import register_energy, register_unit
from setoverlap.operators.registers import pack
from setoverlap.operators.skew import pairs_within

#: Groups whose pairs may all be wanted: at 1,024 registers their broadcast sketches take 16 MB.
MOST_GROUPS = 2_000


def sums(va: Column, vb: Column, m: Column, family: str, layout: str) -> list[Column]:
    if layout == "bucketed":  # an empty bucket is censored at 1
        e = lambda v: F.coalesce(register_unit(v, family), F.lit(1.0))
        pad = m - F.count(F.lit(1))
    else:
        e, pad = (lambda v: register_energy(v, family)), F.lit(0)
    any_ = F.least(va, vb)  # least skips nulls
    b_won, a_won = vb.isNotNull() & (va.isNull() | (vb < va)), va.isNotNull() & (vb.isNull() | (va < vb))
    return [
        m.cast("long").alias("m"), F.count_if(va == vb).alias("k_tie"), F.count_if(b_won).alias("k_b"), F.count_if(a_won).alias("k_a"),
        F.count_if(b_won & va.isNotNull()).alias("k_b_seen"), F.count_if(a_won & vb.isNotNull()).alias("k_a_seen"),
        (F.coalesce(F.sum(e(va)), F.lit(0.0)) + pad).alias("sum_a"), (F.coalesce(F.sum(e(vb)), F.lit(0.0)) + pad).alias("sum_b"), (F.coalesce(F.sum(e(any_)), F.lit(0.0)) + pad).alias("sum_any"),
    ]


def pair_stats(regs: DataFrame, by: list[str] | tuple = (), m: int = 1024, family: str = "xxhash64", layout: str = "k_hash") -> DataFrame:
    """From (by..., k, va, vb) to one row a pair."""
    got = regs.groupBy(*by).agg(*sums(F.col("va"), F.col("vb"), F.lit(m), family, layout))
    return got.withColumn("scale", F.lit(float(m) if layout == "bucketed" else 1.0))


def packed_stats(va: Column, vb: Column, m: int, family: str = "xxhash64", layout: str = "k_hash") -> Column:
    """The six sums (and what buckets add) of two packed sketches of m places, as one struct; nothing is shuffled."""
    censored = layout == "bucketed"
    energy = (lambda v: F.coalesce(register_unit(v, family), F.lit(1.0))) if censored else (lambda v: F.coalesce(register_energy(v, family), F.lit(0.0)))
    one = lambda c: F.when(c, F.lit(1).cast("long")).otherwise(F.lit(0).cast("long"))
    long, real = F.lit(0).cast("long"), F.lit(0.0)
    start = F.struct(long.alias("k_tie"), long.alias("k_b"), long.alias("k_a"), long.alias("k_b_seen"), long.alias("k_a_seen"), real.alias("sum_a"), real.alias("sum_b"), real.alias("sum_any"))

    def add(s: Column, x: Column) -> Column:
        a, b = x["a"], x["b"]
        b_won, a_won = b.isNotNull() & (a.isNull() | (b < a)), a.isNotNull() & (b.isNull() | (a < b))
        return F.struct(
            (s["k_tie"] + one(F.coalesce(a == b, F.lit(False)))).alias("k_tie"), (s["k_b"] + one(b_won)).alias("k_b"), (s["k_a"] + one(a_won)).alias("k_a"),
            (s["k_b_seen"] + one(b_won & a.isNotNull())).alias("k_b_seen"), (s["k_a_seen"] + one(a_won & b.isNotNull())).alias("k_a_seen"),
            (s["sum_a"] + energy(a)).alias("sum_a"), (s["sum_b"] + energy(b)).alias("sum_b"), (s["sum_any"] + energy(F.least(a, b))).alias("sum_any"))

    return F.aggregate(F.zip_with(va, vb, lambda a, b: F.struct(a.alias("a"), b.alias("b"))), start, add)


def pair_stats_between(a: DataFrame, b: DataFrame, m: int, family: str = "xxhash64", layout: str = "k_hash") -> DataFrame:
    """Statistics of joined packed sketches: rows with x, va of `a` and y, vb of `b`, both in one frame or joined by y."""
    both = a if b is None else a.join(b, "y")
    got = both.withColumn("s", packed_stats(F.col("va"), F.col("vb"), m, family, layout)).select("x", "y", "s")
    return got.select("x", "y", F.lit(m).cast("long").alias("m"), "s.*", F.lit(float(m) if layout == "bucketed" else 1.0).alias("scale"))


def pair_stats_arrow(pairs: DataFrame, m: int) -> DataFrame:
    """pair_stats_between for rows x, y, va, vb (longs) of full sketches of the xxhash64 family, in whole batches."""
    names = ["x", "y", "m", "k_tie", "k_b", "k_a", "k_b_seen", "k_a_seen", "sum_a", "sum_b", "sum_any", "scale"]

    def run(batches):
        for batch in batches:
            n = batch.num_rows
            a, b = (batch.column(i).flatten().to_numpy(zero_copy_only=False).reshape(n, m) for i in (2, 3))
            energy = lambda v: -np.log1p(-(v.astype(np.float64) + 0.5) / float(1 << 63)).sum(1)
            tie, won_b, won_a = ((c).sum(1).astype(np.int64) for c in (a == b, b < a, a < b))
            real = [energy(a), energy(b), energy(np.minimum(a, b)), np.ones(n)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *map(pa.array, [np.full(n, m, np.int64), tie, won_b, won_a, won_b, won_a, *real])], names)

    return pairs.select("x", "y", "va", "vb").mapInArrow(run, ", ".join(f"{c} {'double' if c[:3] in ('sum', 'sca') else 'long'}" for c in names))


def pair_stats_two(regs_a: DataFrame, group_a: str, regs_b: DataFrame, group_b: str, pairs: DataFrame, m: int, family: str = "xxhash64", layout: str = "k_hash") -> DataFrame:
    """Statistics of the pairs (x, y), x a group of the first register table and y one of the second."""
    a, b = pack(regs_a, [group_a], m).toDF("x", "va"), pack(regs_b, [group_b], m).toDF("y", "vb")
    return pair_stats_between(pairs.select("x", "y").join(a, "x"), b, m, family, layout)


def pair_stats_all(regs: DataFrame, group: str, m: int, family: str = "xxhash64", pairs: DataFrame | None = None, layout: str = "k_hash", most_groups: int = MOST_GROUPS) -> DataFrame:
    """Statistics of group pairs (x < y) out of packed sketches, one row a group and pair, never one a register.

    `pairs` (x, y) restricts them to candidates, each sketch joined on its group. Without it all pairs are wanted: the
    groups must be few (counted first), and the packed table is broadcast.
    """
    packed = pack(regs, [group], m)
    a, b = packed.toDF("x", "va"), packed.toDF("y", "vb")
    if pairs is not None:
        return pair_stats_between(pairs.select("x", "y").join(a, "x"), b, m, family, layout)
    n = regs.select(group).distinct().limit(most_groups + 1).count()
    if n > most_groups:
        raise ValueError(f"all pairs of more than {most_groups} groups: give candidates")
    parts = int(regs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    both = a.repartition(max(2, min(parts, n)), "x").join(F.broadcast(b), F.col("x") < F.col("y"))
    return pair_stats_between(both, None, m, family, layout)


def leading_pairs(regs: DataFrame, group: str, most: int) -> DataFrame:
    """(x, y), x < y, that hold the `most` pairs of largest estimated overlap (ties by x, y) of any number of groups: all
    pairs that tie in some register, and, since every other pair's estimate is 0, the first pairs in order of x, y."""
    regs = regs.select(group, "k", "v").where(F.col(group).isNotNull())
    tied = pairs_within(regs, ["k", "v"], group).select("x", "y").distinct()
    # fewer than `most` tied pairs leave at least as many others among the first 2 * most, which these groups hold
    first = regs.select(F.col(group).alias("x")).distinct().orderBy("x").limit(2 * most + 1)
    rest = first.join(first.withColumnRenamed("x", "y"), F.col("x") < F.col("y"))
    return tied.unionByName(rest).distinct()


def jaccard_estimate() -> Column:
    """Share of registers that tie among those that any side fills."""
    return F.try_divide(F.col("k_tie").cast("double"), (F.col("k_tie") + F.col("k_a") + F.col("k_b")).cast("double"))
