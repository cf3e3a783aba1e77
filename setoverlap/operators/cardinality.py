"""Sizes of single sets and unions: from max sketches, from scratch-built log-log registers, native, exact."""

from __future__ import annotations

import math
from functools import lru_cache

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setoverlap.functions.hashing import BITS, unit_hash


def card_from_registers(sum_e: Column, m: Column, unbiased: bool = False) -> Column:
    """m / sum of energies (maximum likelihood), or (m - 1) / sum; 0 for an empty set."""
    return F.when(sum_e > 0, F.try_divide((m - 1 if unbiased else m).cast("double"), sum_e)).otherwise(0.0)


@lru_cache(maxsize=64)
def hll_alpha(m: int, steps: int = 20_000) -> float:
    """1 / (m * integral over u > 0 of log2((2 + u) / (1 + u))^m), by the trapezoid rule on a transformed axis."""
    total, step = 0.0, 1.0 / steps
    for i in range(1, steps):
        t = i * step
        u = t / (1 - t)
        total += math.log2((2 + u) / (1 + u)) ** m / (1 - t) ** 2
    return 1.0 / (m * (total + 0.5) * step)


def hll_registers(df: DataFrame, elem: Column | str, by: list[str] | tuple = (), m: int = 512, family: str = "xxhash64", rank_base: int = 1) -> DataFrame:
    """(by..., bucket, rank): the largest rank, rank = base + leading zeros of the second hash."""
    elem = F.col(elem) if isinstance(elem, str) else elem
    v = unit_hash(F.col("e"), F.lit(0), family)
    rank = F.lit(BITS[family] + rank_base) - F.when(v > 0, F.length(F.bin(v))).otherwise(0)
    rows = df.select(*by, elem.alias("e")).where(F.col("e").isNotNull())
    return rows.select(*by, F.pmod(unit_hash(F.col("e"), F.lit(1), family), F.lit(m)).cast("int").alias("bucket"), rank.cast("int").alias("rank")).groupBy(*by, "bucket").agg(F.max("rank").alias("rank"))


def hll_estimate(regs: DataFrame, by: list[str] | tuple, m: int, small_range: str = "none") -> DataFrame:
    """card_hll; buckets never hit count as rank 0; small_range='linear' counts empties below 2.5 m, 'always' counts them at
    any size (with none left, as one: m ln m is the most it can say)."""
    got = regs.groupBy(*by).agg((F.sum(F.pow(F.lit(2.0), -F.col("rank"))) + (m - F.count(F.lit(1)))).alias("inverse"), (m - F.count(F.lit(1))).alias("empties"))
    raw = F.lit(hll_alpha(m) * m * m) / F.col("inverse")
    linear = m * F.ln(F.lit(float(m)) / F.greatest(F.col("empties"), F.lit(1)))
    if small_range == "linear":
        raw = F.when((raw <= 2.5 * m) & (F.col("empties") > 0), linear).otherwise(raw)
    elif small_range == "always":
        raw = linear
    return got.withColumn("card_hll", raw).drop("inverse")


def hll_variance(c: Column, m: Column, variant: str = "lemma") -> Column:
    return c * c / m * (1.0 if variant == "lemma" else 1.04 * 1.04)


def native_cardinality(df: DataFrame, elem: str, by: list[str] | tuple = ()) -> DataFrame:
    """Spark's own three estimates, as a cross-check."""
    return df.groupBy(*by).agg(F.approx_count_distinct(elem, 0.01).alias("card_approx"), F.hll_sketch_estimate(F.hll_sketch_agg(elem, 14)).alias("card_hll_native"), F.theta_sketch_estimate(F.theta_sketch_agg(elem)).alias("card_theta"))


def native_theta_intersection(df: DataFrame, elem: str, in_a: Column, in_b: Column) -> DataFrame:
    got = df.agg(F.theta_sketch_agg(F.when(in_a, F.col(elem))).alias("a"), F.theta_sketch_agg(F.when(in_b, F.col(elem))).alias("b"))
    return got.select(F.theta_sketch_estimate(F.theta_intersection("a", "b")).alias("card_both"))


#: Where a scheme's sizes may come from; the registers themselves are the default and need no second sketch.
SOURCES = ("registers", "hll", "native_hll", "exact")


def pair_cardinalities(df: DataFrame, elem: Column | str, in_a: Column, in_b: Column, source: str, m: int = 1024) -> DataFrame:
    """One row c_a, c_b, c_any: sizes of two sets and their union from one scan, by log-log registers of our own (the
    union's are merged from the sides'), by Spark's sketch, or exactly."""
    elem = F.col(elem) if isinstance(elem, str) else elem
    rows = df.select(elem.alias("e"), in_a.alias("in_a"), in_b.alias("in_b")).where("e is not null and (in_a or in_b)")
    side = lambda c: F.when(F.col(c), F.col("e"))
    if source == "exact":
        return rows.agg(F.countDistinct(side("in_a")).alias("c_a"), F.countDistinct(side("in_b")).alias("c_b"), F.countDistinct("e").alias("c_any")).select(*[F.col(c).cast("double").alias(c) for c in ("c_a", "c_b", "c_any")])
    if source == "native_hll":
        sketches = rows.agg(F.hll_sketch_agg(side("in_a"), 14).alias("a"), F.hll_sketch_agg(side("in_b"), 14).alias("b"))
        size = lambda c: F.hll_sketch_estimate(c).cast("double")
        return sketches.select(size(F.col("a")).alias("c_a"), size(F.col("b")).alias("c_b"), size(F.hll_union("a", "b")).alias("c_any"))
    if source != "hll":
        raise ValueError(f"source is one of {SOURCES[1:]} (registers need no call)")
    sides = rows.select("e", F.explode(F.array_compact(F.array(F.when(F.col("in_a"), F.lit("c_a")), F.when(F.col("in_b"), F.lit("c_b"))))).alias("side"))
    regs = hll_registers(sides, "e", ["side"], m)
    merged = regs.groupBy("bucket").agg(F.max("rank").alias("rank")).select(F.lit("c_any").alias("side"), "bucket", "rank")
    return hll_estimate(regs.unionByName(merged), ["side"], m, "linear").groupBy().pivot("side", ["c_a", "c_b", "c_any"]).agg(F.first("card_hll"))


def exact_cardinality(df: DataFrame, elem: str, by: list[str] | tuple = ()) -> DataFrame:
    return df.groupBy(*by).agg(F.countDistinct(elem).alias("card"))
