"""Sketches: the best hash of each of m functions for each set. Building takes one pass and no distinct; merging is min."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setoverlap.functions.hashing import element_hash, mixed_long, slot_hash, slot_seeds

LAYOUTS = ("k_hash", "bucketed")
#: Elements that the Arrow engine mixes with all functions at once: 8 bytes x m x BLOCK of scratch memory.
BLOCK = 256


def slots(df: DataFrame, elem: Column, m: int, family: str = "xxhash64", seed: int = 0, layout: str = "k_hash") -> DataFrame:
    """Adds k and v. k_hash: a row for each function, pipelined into partial aggregation; bucketed: one row, two hashes."""
    if layout not in LAYOUTS:
        raise ValueError(f"layout is one of {LAYOUTS}")
    df = df.withColumn("elem_", elem).where(F.col("elem_").isNotNull()).withColumn("elem_", element_hash(F.col("elem_"), family, seed))
    if layout == "bucketed":
        return df.withColumns({"k": F.pmod(slot_hash(F.col("elem_"), F.lit(1), family), F.lit(m)).cast("int"), "v": slot_hash(F.col("elem_"), F.lit(0), family)}).drop("elem_")
    return df.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(m - 1)))).withColumn("v", slot_hash(F.col("elem_"), F.col("k"), family)).drop("elem_")


def build_registers(df: DataFrame, elem: Column | str, by: list[str] | tuple = (), m: int = 1024, family: str = "xxhash64", seed: int = 0, layout: str = "k_hash", engine: str = "sql") -> DataFrame:
    """(by..., k, v): one row a register; at most partitions x groups x m rows are shuffled. engine="arrow" gives the
    same registers of the xxhash64 family, by block minima in NumPy."""
    elem = F.col(elem) if isinstance(elem, str) else elem
    if engine == "arrow":
        if family != "xxhash64":
            raise ValueError("the arrow engine computes the xxhash64 family alone")
        hashed = df.select(*by, F.when(elem.isNotNull(), element_hash(elem, family, seed)).alias("h")).where("h is not null")
        return _arrow_registers(hashed, list(by), m, layout)
    return slots(df.select(*by, elem.alias("e")), F.col("e"), m, family, seed, layout).groupBy(*by, "k").agg(F.min("v").alias("v"))


def block_minima(h: np.ndarray, m: int, layout: str = "k_hash") -> np.ndarray:
    """Masked register values of element hashes (uint64); the largest uint64 where a bucket is empty."""
    best, mask = np.full(m, np.iinfo(np.uint64).max, np.uint64), np.uint64((1 << 63) - 1)
    if layout == "bucketed":
        value, bucket = slot_seeds(2)
        np.minimum.at(best, ((mixed_long(h, bucket) & mask) % np.uint64(m)).astype(np.int64), mixed_long(h, value) & mask)
        return best
    seeds = slot_seeds(m)[:, None]
    for at in range(0, len(h), BLOCK):
        np.minimum(best, (mixed_long(h[None, at : at + BLOCK], seeds) & mask).min(1), out=best)
    return best


def _arrow_registers(df: DataFrame, by: list[str], m: int, layout: str) -> DataFrame:
    """Rows never multiply by m in the JVM: a batch gives at most m rows a group."""
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in df.select(*by).schema.fields] + ["k int", "v long"])
    names = [*by, "k", "v"]

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            frame = batch.to_pandas()
            groups = [((), frame)] if not by else frame.groupby(by, sort=False, dropna=False)
            for key, g in groups:
                best = block_minima(np.unique(g["h"].to_numpy().view(np.uint64)), m, layout)
                at = np.flatnonzero(best < np.uint64(1 << 63))
                key = key if isinstance(key, tuple) else (key,)
                cols = [pa.array([p] * len(at), t, from_pandas=True) for p, t in zip(key, batch.select(by).schema.types, strict=True)] if by else []
                yield pa.RecordBatch.from_arrays([*cols, pa.array(at.astype(np.int32)), pa.array(best[at].astype(np.int64))], names)

    return df.mapInArrow(run, schema).groupBy(*by, "k").agg(F.min("v").alias("v"))


def sketch_arrays(sets: DataFrame, group: str, m: int) -> DataFrame:
    """(group, regs): what build_registers and pack give for sets that are rows already: `h`, an array of element hashes
    of the xxhash64 family. Nothing is exploded or shuffled; empty sets have no row."""

    def run(batches):
        for batch in batches:
            col = batch.column(1)
            flat, ends = col.values.to_numpy(zero_copy_only=False).view(np.uint64), col.offsets.to_numpy()
            full = [i for i in range(len(col)) if ends[i + 1] > ends[i]]
            best = np.stack([block_minima(flat[ends[i] : ends[i + 1]], m) for i in full]).astype(np.int64) if full else np.zeros((0, m), np.int64)
            regs = pa.ListArray.from_arrays(pa.array(np.arange(0, (len(full) + 1) * m, m, dtype=np.int32)), pa.array(best.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(full, pa.int64())), regs], [group, "regs"])

    kind = sets.schema[group].dataType.simpleString()
    return sets.select(group, "h").where("h is not null").mapInArrow(run, f"`{group}` {kind}, regs array<long>")


def merge_registers(regs: DataFrame, by: list[str] | tuple = ()) -> DataFrame:
    """Registers of the union of the sets that `by` puts together (also a roll-up: never a second scan)."""
    return regs.groupBy(*by, "k").agg(F.min("v").alias("v"))


def cube_registers(regs: DataFrame, by: list[str]) -> DataFrame:
    """Registers of every grouping of `by`, merged out of the finest; grouping columns are null where rolled up."""
    return regs.cube(*by, "k").agg(F.min("v").alias("v"), F.grouping_id().alias("gid")).where("k is not null and gid % 2 = 0").drop("gid")


def pack(regs: DataFrame, by: list[str], m: int | None = None) -> DataFrame:
    """One row a group: regs ARRAY<BIGINT> in order of k; with m, empty buckets are null, so that every array has m places."""
    rows = F.collect_list(F.struct("k", "v"))
    if m is not None:  # (k, null) sorts before (k, v): the last of each k stays
        rows = F.concat(rows, F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda k: F.struct(k.alias("k"), F.lit(None).cast("long").alias("v"))))
    packed = regs.groupBy(*by).agg(F.sort_array(rows).alias("regs"))
    at = F.col("regs")
    last = F.filter(at, lambda x, i: F.coalesce(F.get(at, i + 1)["k"] != x["k"], F.lit(True))) if m is not None else at
    return packed.withColumn("regs", F.transform(last, lambda x: x["v"]))


def union_packed(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.least(x, y))


def sketch_bytes(regs: Column) -> Column:
    return F.size(regs) * 8


def pair_registers(df: DataFrame, elem: Column | str, in_a: Column, in_b: Column, by: list[str] | tuple = (), m: int = 1024, family: str = "xxhash64", seed: int = 0, layout: str = "k_hash") -> DataFrame:
    """(by..., k, va, vb): registers of both sides out of one scan; rows may belong to both."""
    elem = F.col(elem) if isinstance(elem, str) else elem
    rows = df.select(*by, elem.alias("e"), in_a.alias("in_a"), in_b.alias("in_b")).where("in_a or in_b")
    return slots(rows, F.col("e"), m, family, seed, layout).groupBy(*by, "k").agg(F.min(F.when(F.col("in_a"), F.col("v"))).alias("va"), F.min(F.when(F.col("in_b"), F.col("v"))).alias("vb"))
