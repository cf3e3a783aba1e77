"""Tables in and sketches out: parquet, csv, json, orc and text readers, and a sketch store partitioned by set."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, prefix: str, names: list[str]) -> None:
    """Tables as temporary views `prefix` + name, for SQL."""
    for name in names:
        load_table(spark, sf_dir, name).createOrReplaceTempView(f"{prefix}{name}")


def load_file(spark: SparkSession, path: str, kind: str = "parquet", schema=None) -> DataFrame:
    """Any of parquet, orc, csv, json (schema given), text."""
    reader = spark.read.schema(schema) if schema is not None else spark.read
    if kind == "csv":
        return reader.option("header", True).csv(path)
    return reader.format(kind).load(path)


def save_registers(regs: DataFrame, path: str, dataset: str, snapshot: str, kind: str = "xxhash64-0-k_hash") -> None:
    """Append one snapshot of long registers; partitions are (kind, dataset, snapshot), so readers prune. kind: family,
    seed and layout; registers of two kinds have nothing in common and are never read together."""
    regs.withColumns({"kind": F.lit(kind), "dataset": F.lit(dataset), "snapshot": F.lit(snapshot)}).write.mode("append").partitionBy("kind", "dataset", "snapshot").parquet(path)


def load_registers(spark: SparkSession, path: str, dataset: str | None = None, as_of: str | None = None, kind: str = "xxhash64-0-k_hash") -> DataFrame:
    """Registers of one kind, of a dataset; with as_of, each group's latest snapshot not after it."""
    got = spark.read.parquet(path).where(F.col("kind") == kind).drop("kind")
    got = got if dataset is None else got.where(F.col("dataset") == dataset)
    if as_of is None:
        return got
    got = got.where(F.col("snapshot") <= F.lit(as_of))
    latest = got.groupBy("dataset").agg(F.max("snapshot").alias("latest"))
    return got.join(F.broadcast(latest), "dataset").where("snapshot = latest").drop("latest")  # one row a dataset
