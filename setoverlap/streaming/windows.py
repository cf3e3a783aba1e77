"""Shared flows per event-time window on streams: one tagged input, minima per (window, k), six sums per window.

Registers are idempotent, so rows delivered twice change nothing; rows later than the watermark are dropped. Windows are
emitted in append mode once the watermark has passed them: a closing row far in the future (`with_closing_row`) lets a
bounded replay emit its last window too, while the window of the closing row itself never ends.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import StructType

from setoverlap.functions.hashing import element_hash, slot_hash
from setoverlap.operators.pairstats import sums
from setoverlap.operators.registers import block_minima, build_registers
from setoverlap.session import shared_folder


def read_events(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events.parquet").parquet(sf_dir)


#: Bytes of a row group of a replayed file: a micro-batch of one file is still read by many tasks.
ROW_GROUP = 1 << 20


def replay(spark: SparkSession, batches: list[DataFrame]) -> DataFrame:
    """A stream that delivers these tables one after the other, each as one micro-batch."""
    path = shared_folder(spark, "replay")
    for b in batches:
        b.coalesce(1).write.mode("append").option("parquet.block.size", ROW_GROUP).parquet(path)  # one file a batch: files are taken in order of their time
    return spark.readStream.schema(batches[0].schema).option("maxFilesPerTrigger", 1).parquet(path)


def closing_row(events: DataFrame, like: Column, ts: str = "ts", days: int = 400) -> DataFrame:
    """One event that `like` holds for, moved far past the last: filters of a query must let it through, since Spark
    takes them before it looks at the time."""
    kind = events.schema[ts].dataType
    return events.where(like).orderBy(F.desc(ts)).limit(1).withColumn(ts, (F.col(ts) + F.expr(f"INTERVAL {days} DAYS")).cast(kind)).select(events.columns)


def timed(df: DataFrame, ts: str = "ts", delay: str = "10 minutes") -> DataFrame:
    """Event time as TIMESTAMP (session zone; watermarks refuse the zone-less type) with a watermark."""
    return df.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def windowed_registers(df: DataFrame, elem: str, in_a: Column, in_b: Column, window: Column, m: int, family: str = "xxhash64", over: tuple | None = None) -> DataFrame:
    """(w, k, va, vb); window: F.window(...) or F.session_window(...). Rows of neither side open no window. over: duration
    and slide of sliding windows whose panes `window` gives (the slide divides the duration and is the pane's length): a
    row is hashed once for its pane, and minima of panes, not rows, go to every window that holds them."""
    rows = df.select(window.alias("w"), F.col(elem).alias("e"), in_a.alias("in_a"), in_b.alias("in_b")).where("e is not null and (in_a or in_b)")
    rows = rows.withColumn("e", element_hash(F.col("e"), family)).withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(m - 1)))).withColumn("v", slot_hash(F.col("e"), F.col("k"), family))
    regs = rows.groupBy("w", "k").agg(F.min(F.when(F.col("in_a"), F.col("v"))).alias("va"), F.min(F.when(F.col("in_b"), F.col("v"))).alias("vb"))
    if over is None:
        return regs
    return regs.groupBy(F.window("w", *over).alias("w"), "k").agg(F.min("va").alias("va"), F.min("vb").alias("vb"))


def windowed_stats(registers: DataFrame, m: int, family: str = "xxhash64", session: bool = False) -> DataFrame:
    """Six sums a window: on a stream a second, chained aggregation in append mode. Sessions are grouped by their ends
    inside a window of a second at their last instant, since a stream cannot group by a session alone."""
    if session:
        last = F.window_time("w") if registers.isStreaming else F.col("w.end")
        at = registers.select(F.window(last, "1 second").alias("at"), F.col("w.start").alias("s"), F.col("w.end").alias("e"), "va", "vb")
        got = at.groupBy("at", "s", "e").agg(*sums(F.col("va"), F.col("vb"), F.lit(m), family, "k_hash"))
        return got.withColumn("w", F.struct(F.col("s").alias("start"), F.col("e").alias("end"))).drop("at", "s", "e").withColumn("scale", F.lit(1.0))
    return registers.groupBy("w").agg(*sums(F.col("va"), F.col("vb"), F.lit(m), family, "k_hash")).withColumn("scale", F.lit(1.0))


def run_to_table(stream: DataFrame, checkpoint: str | None = None) -> DataFrame:
    """Drive a stream over what is available now into Parquet files of the shared folder, and read them."""
    spark = stream.sparkSession
    path = shared_folder(spark, "sink")
    q = stream.writeStream.outputMode("append").format("parquet").option("path", path).option("checkpointLocation", checkpoint or shared_folder(spark, "stream")).trigger(availableNow=True).start()
    try:
        q.awaitTermination()
    finally:
        q.stop()
    return spark.read.schema(stream.schema).parquet(path)


def run_batches(stream: DataFrame, keep: Callable[[DataFrame, int], None], mode: str = "update", checkpoint: str | None = None) -> None:
    """Drive a stream over what is available now into a function of (batch, epoch)."""
    q = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", checkpoint or shared_folder(stream.sparkSession, "stream")).trigger(availableNow=True).start()
    try:
        q.awaitTermination()
    finally:
        q.stop()


def running_registers(stream: DataFrame, elem: str, group: str, m: int, path: str, checkpoint: str, family: str = "xxhash64"):
    """Running sketches by foreachBatch: each micro-batch is reduced and appended to a store that readers merge by min."""

    def keep(batch: DataFrame, epoch: int) -> None:
        build_registers(batch, elem, [group], m, family).withColumn("epoch", F.lit(epoch)).write.mode("append").partitionBy("epoch").parquet(path)

    return stream.writeStream.foreachBatch(keep).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def running_overlap(stream: DataFrame, elem: str, group: str, in_a: Column, in_b: Column, m: int) -> DataFrame:
    """(group, rows, k_tie, k_b, k_a, sum_a, sum_b, sum_any) after each micro-batch of a group: both sides' registers are
    the state of a stateful operator, 16 m bytes a group whatever the stream's length."""
    rows = stream.select(F.col(group).cast("string").alias("g"), element_hash(F.col(elem)).alias("h"), in_a.alias("in_a"), in_b.alias("in_b")).where("h is not null and (in_a or in_b)")

    def update(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        import numpy as np

        top = np.uint64((1 << 64) - 1)
        seen, raw = state.get if state.exists else (0, bytes(0))
        best = np.frombuffer(raw, np.uint64).reshape(2, m).copy() if raw else np.full((2, m), top, np.uint64)
        for f in frames:
            seen += len(f)
            h = f["h"].to_numpy().astype(np.int64).view(np.uint64)
            for side, name in enumerate(("in_a", "in_b")):
                np.minimum(best[side], block_minima(np.unique(h[f[name].to_numpy(bool)]), m), out=best[side])
        state.update((seen, best.tobytes()))
        a, b = best
        e = np.where(best == top, 0.0, -np.log1p(-(best.astype(np.float64) + 0.5) / float(1 << 63)))
        both = np.minimum(a, b)
        any_ = np.where(both == top, 0.0, -np.log1p(-(both.astype(np.float64) + 0.5) / float(1 << 63)))
        yield pd.DataFrame([(key[0], seen, int(((a == b) & (a != top)).sum()), int((b < a).sum()), int((a < b).sum()), e[0].sum(), e[1].sum(), any_.sum())], columns=["g", "n_rows", "k_tie", "k_b", "k_a", "sum_a", "sum_b", "sum_any"])

    out = "g string, n_rows long, k_tie long, k_b long, k_a long, sum_a double, sum_b double, sum_any double"
    return rows.groupBy("g").applyInPandasWithState(update, StructType.fromDDL(out), StructType.fromDDL("n_rows long, regs binary"), "update", GroupStateTimeout.NoTimeout)
