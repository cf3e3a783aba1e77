"""Pairs of many sets: banded candidates over registers or exact prefixes instead of a cross product.

Sets that are equal (or have equal sketches) are one class, named by its smallest group: pairs are formed between
classes, and `members` says which groups a class holds, so copies are never expanded into their pairs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setoverlap.operators import prefixes
from setoverlap.operators.pairstats import pair_stats_arrow
from setoverlap.operators.registers import pack
from setoverlap.operators.skew import join_back, pairs_within
from setoverlap.session import materialised


def _digest(values: Column) -> Column:
    """128 bits of an array of hashes."""
    return F.md5(F.array_join(F.transform(values, lambda v: v.cast("string")), ",").cast("binary"))


def members(rows: DataFrame, group: str, values: str) -> DataFrame:
    """(member, class): each group's class is the smallest group with the same array of values."""
    keyed = rows.select(F.col(group).alias("member"), _digest(F.col(values)).alias("d"))
    first = keyed.groupBy("d").agg(F.min("member").alias("class"), F.count("*").alias("n"))
    return join_back(keyed, first, ["d"], "member", "n").select("member", "class")


def band_candidates(regs: DataFrame, group: str, rows_per_band: int = 4) -> DataFrame:
    """(x, y), x < y, for classes of equal sketches that agree in all registers of some band; a pair with Jaccard J is
    found with probability 1 - (1 - J^r)^(m/r)."""
    return packed_candidates(pack(regs, [group]), group, rows_per_band)


def packed_candidates(packed: DataFrame, group: str, rows_per_band: int = 4) -> DataFrame:
    """band_candidates of packed sketches (group long, regs): a key of one class is dropped where it arrives."""
    keyed = packed.withColumn("d", _digest(F.col("regs")))
    one = keyed.groupBy("d").agg(F.min_by("regs", group).alias("regs"), F.min(group).alias("x"))
    band = lambda i: F.xxhash64(i, F.slice("regs", i * rows_per_band + 1, rows_per_band))
    rows = one.select(F.explode(F.transform(F.sequence(F.lit(0), F.floor(F.size("regs") / rows_per_band).cast("int") - 1), band)).alias("key"), F.col("x").cast("long").alias("x"))
    return prefixes.counted_pairs(rows).select("x", "y")


def similar_pairs(packed: DataFrame, group: str, m: int, rows_per_band: int = 4) -> DataFrame:
    """Pair statistics of the banded candidates of packed sketches without empty places."""
    a, b = packed.toDF("x", "va"), packed.toDF("y", "vb")
    return pair_stats_arrow(packed_candidates(packed, group, rows_per_band).join(a, "x").join(b, "y"), m)


def exact_pair_overlaps(sets: DataFrame, group: str, elem: str) -> DataFrame:
    """(x, y, card_both, card_any) of all pairs that share an element; elements that many groups hold are dealt out in blocks."""
    s = materialised(sets.select(group, elem).distinct())
    n = s.groupBy(group).agg(F.count("*").alias("n"))
    both = pairs_within(s, [elem], group).groupBy("x", "y").agg(F.count("*").alias("card_both"))
    got = both.join(n.toDF("x", "nx"), "x").join(n.toDF("y", "ny"), "y")
    return got.select("x", "y", "card_both", (F.col("nx") + F.col("ny") - F.col("card_both")).alias("card_any"))


def element_arrays(sets: DataFrame, group: str, elem: str) -> DataFrame:
    """(group, h): each set's distinct elements as 64-bit hashes in order."""
    return sets.groupBy(group).agg(F.array_sort(F.collect_set(F.xxhash64(elem))).alias("h"))


def exact_similar_pairs(sets: DataFrame, group: str, elem: str, over: int = 1, under: int = 2) -> DataFrame:
    """(x, y, card_both, card_any) with card_both / card_any >= over / under, exactly, of sets given as rows (group,
    elem): prefixes.similar_pairs over their arrays, which are written once."""
    return prefixes.similar_pairs(materialised(element_arrays(sets, group, elem)), group, F.col("h"), over, under)
