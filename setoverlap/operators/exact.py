"""Exact baselines: the naive nested scan (for tiny inputs) and relational forms that shuffle the distinct elements."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setoverlap.functions.hashing import unit_hash

NAIVE_LIMIT = 10_000


def exact_intersection_naive(a: DataFrame, b: DataFrame) -> DataFrame:
    """Every element of A against every element of B, then the distinct hits; refuses inputs above NAIVE_LIMIT rows."""
    if max(a.limit(NAIVE_LIMIT + 1).count(), b.limit(NAIVE_LIMIT + 1).count()) > NAIVE_LIMIT:
        raise ValueError("the nested scan is quadratic; use exact_intersection")
    return a.toDF("x").crossJoin(b.toDF("y")).where("x = y").select(F.countDistinct("x").alias("card_both"))


def exact_intersection(a: DataFrame, b: DataFrame, how: str = "intersect") -> DataFrame:
    a, b = a.toDF("e"), b.toDF("e")
    got = {"intersect": lambda: a.intersect(b), "semi": lambda: a.join(b, "e", "left_semi").distinct(), "inner": lambda: a.distinct().join(b.distinct(), "e")}[how]()
    return got.agg(F.count("e").alias("card_both"))


def private_part(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.toDF("e").join(b.toDF("e"), "e", "left_anti").agg(F.countDistinct("e").alias("only_a"))


def coordinated_sample(df: DataFrame, elem: str, one_in: int, family: str = "xxhash64") -> DataFrame:
    """Rows of every element whose hash falls into one of `one_in` classes: the same elements on all sides, unlike a row sample."""
    return df.where(F.pmod(unit_hash(F.col(elem), F.lit(0), family), F.lit(one_in)) == 0)


def exact_sizes(df: DataFrame, elem: Column | str, in_a: Column, in_b: Column, by: list[str] | tuple = ()) -> DataFrame:
    """All six sizes out of one scan: side flags for each element, then counts."""
    elem = F.col(elem) if isinstance(elem, str) else elem
    flags = df.select(*by, elem.alias("e"), in_a.alias("in_a"), in_b.alias("in_b")).where("e is not null and (in_a or in_b)").groupBy(*by, "e").agg(F.bool_or("in_a").alias("a"), F.bool_or("in_b").alias("b"))
    n = lambda cond, name: F.count_if(cond).alias(name)
    a, b = F.col("a"), F.col("b")
    return flags.groupBy(*by).agg(n(a, "card_a"), n(b, "card_b"), n(a & b, "card_both"), n(a | b, "card_any"), n(a & ~b, "only_a"), n(b & ~a, "only_b"))
