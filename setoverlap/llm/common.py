"""Helpers that the corpus operators share: reading tables, Arrow row maps, shared scratch folders."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setoverlap.session import ship_package

#: Rows that cross to Python at once; long texts make a batch large, so it stays well under Spark's 10,000.
ROWS_PER_BATCH = 512


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small_batches(spark: SparkSession) -> None:
    """Bound the rows of an Arrow batch (a runtime setting; a lower value of the session stays) and ship the package."""
    ship_package(spark)
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key, "10000"))
    if now <= 0 or now > ROWS_PER_BATCH:
        spark.conf.set(key, str(ROWS_PER_BATCH))


def id_and_text(df: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The two columns that scans need; a null text reads as empty, other columns are never read."""
    return df.select(F.col(id_col).cast("long").alias(id_col), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))


def map_rows(df: DataFrame, setup: Callable[[], Callable[[int | None, str], tuple]], schema: str) -> DataFrame:
    """One output row for each (id, text) row. `setup` runs once in a task and returns the row function."""
    small_batches(df.sparkSession)
    names = [part.split()[0] for part in schema.split(",")]
    kinds = {"long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "boolean": pa.bool_(), "string": pa.string(), "binary": pa.binary(), "array<long>": pa.list_(pa.int64()), "array<int>": pa.list_(pa.int32())}
    types = [kinds[part.split()[1]] for part in schema.split(",")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        row = setup()
        for batch in batches:
            out = [row(i, t) for i, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)]
            columns = list(zip(*out, strict=True)) if out else [()] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, types, strict=True)], names)

    return df.mapInArrow(run, schema)


def fenced(df: DataFrame) -> DataFrame:
    """df with its last projection closed to filters from above: pushed below, they would repeat its expressions."""
    name = "fence"
    while name in df.columns:
        name += "_"
    return df.withColumn(name, F.monotonically_increasing_id()).where(F.col(name) >= 0).drop(name)


def scratch(spark: SparkSession) -> str:
    """A new path under spark.checkpoint.dir, the folder that driver and executors share.

    Only where the session has none (local tests) a temporary folder of this machine is set.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        folder = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = folder.get() if folder.isDefined() else None
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        import tempfile

        base = "file://" + tempfile.mkdtemp(prefix="scratch-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/work-{uuid.uuid4().hex}"


def materialised(df: DataFrame) -> DataFrame:
    """Write to the shared folder as Parquet and read back: cuts the lineage, survives lost executors."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete what `materialised` wrote for these tables, once nothing reads them any more."""
    for df in tables:
        sc = df.sparkSession.sparkContext
        path = sc._jvm.org.apache.hadoop.fs.Path(df.scratch_path)
        path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)


def spans_digest(spans: list[tuple[int, int, str, int]]) -> str:
    """kind:start:end, comma-joined, of (start, kind's order, kind, end) in order."""
    return ",".join(f"{k}:{s}:{e}" for s, _, k, e in sorted(spans))
