"""Joins that hold when one key has a third of all rows: hot keys are found by count, and their rows dealt out.

A key is hot when it has at least one row in HOT_SHARE of all, so at most HOT_SHARE keys are hot and their list may be
broadcast, whatever the input's size.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

HOT_SHARE = 1000
#: Rows of one key that meet all others in one task.
BLOCK = 1024


def _hot(counts: DataFrame, keys: list[str], least: int) -> DataFrame:
    total = F.broadcast(counts.agg(F.sum("n_").alias("total_")))  # one row
    return counts.where(F.col("n_") > least).crossJoin(total).where(F.col("n_") * HOT_SHARE >= F.col("total_")).select(*keys, F.col("n_").alias("hot_"))


def join_back(rows: DataFrame, stats: DataFrame, keys: list[str], other: str, count: str) -> DataFrame:
    """rows joined with their keys' statistics (one row a key; `count` is its row count): rows of hot keys are dealt by
    `other` over as many salts as there are shuffle partitions, and only hot statistics are copied."""
    salts = max(2, min(4096, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    hot = F.broadcast(_hot(stats.withColumn("n_", F.col(count)), keys, BLOCK))
    dealt = rows.join(hot, keys, "left").withColumn("salt_", F.when(F.col("hot_").isNotNull(), F.pmod(F.xxhash64(other), F.lit(salts)).cast("int")).otherwise(0)).drop("hot_")
    copies = F.when(F.col("hot_").isNotNull(), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0)))
    return dealt.join(stats.join(hot, keys, "left").withColumn("salt_", F.explode(copies)).drop("hot_"), [*keys, "salt_"]).drop("salt_")


def pairs_within(rows: DataFrame, keys: list[str], member: str) -> DataFrame:
    """(keys..., x, y), x < y, of distinct members that share a key. Members of a hot key are dealt into blocks of about
    BLOCK, and each two blocks meet in a task of their own."""
    rows = rows.select(*keys, F.col(member).alias("x"))
    counts = rows.groupBy(*keys).agg(F.count("*").alias("n_")).where("n_ > 1")
    hot = F.broadcast(_hot(counts, keys, BLOCK).withColumn("blocks_", F.ceil(F.col("hot_") / BLOCK).cast("int")).drop("hot_"))
    dealt = rows.join(hot, keys, "left").withColumn("blocks_", F.coalesce("blocks_", F.lit(1))).withColumn("mine_", F.pmod(F.xxhash64("x"), F.col("blocks_")).cast("int"))
    left = dealt.select(*keys, F.col("mine_").alias("i_"), F.explode(F.sequence(F.col("mine_"), F.col("blocks_") - 1)).alias("j_"), "x")
    right = dealt.select(*keys, F.explode(F.sequence(F.lit(0), F.col("mine_"))).alias("i_"), F.col("mine_").alias("j_"), F.col("x").alias("y"))
    met = left.join(right, [*keys, "i_", "j_"]).where((F.col("i_") < F.col("j_")) & (F.col("x") != F.col("y")) | (F.col("x") < F.col("y")))
    return met.select(*keys, F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y"))
