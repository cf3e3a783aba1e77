"""Hashing of elements to registers. A register holds the smallest masked hash v; x = 1 - (v + 1/2) / 2^bits is the
largest value in (0, 1), and e = -ln x its energy, exponential with the set's size as rate.

The xxhash64 family hashes an element once and then mixes that hash with each function's index, so m functions cost one
hash of the element and m of a BIGINT; the second step is plain integer arithmetic that NumPy repeats bit by bit.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = {"md5": 60, "xxhash64": 63}
# The five primes of the public 64-bit xxHash, and the seed that Spark's xxhash64 starts from.
PRIMES = [np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5)]
SPARK_SEED = np.uint64(42)


def element(*cols: Column | str) -> Column:
    """One hashable value: integers as BIGINT whatever their width, several columns length-prefixed."""
    cols = [F.col(c) if isinstance(c, str) else c for c in cols]
    if len(cols) == 1:
        return cols[0]
    return F.concat(*[F.concat(F.length(c.cast("string")).cast("string"), F.lit("|"), c.cast("string")) for c in cols])


def element_hash(elem: Column, family: str = "xxhash64", seed: int = 0) -> Column:
    """What is computed once for an element: its 64-bit hash, or the text that md5 takes."""
    if family not in BITS:
        raise ValueError(f"unknown hash family {family}")
    if family == "xxhash64":
        return F.xxhash64(F.lit(seed).cast("long"), elem)
    return F.concat(F.lit(":" if not seed else f":{seed}:"), elem.cast("string"))


def slot_hash(hashed: Column, k: Column, family: str = "xxhash64") -> Column:
    """Masked hash of function k: 63 bits, or 60 bits of md5 where another engine must agree."""
    if family == "xxhash64":
        return F.xxhash64(k.cast("long"), hashed).bitwiseAND(F.lit((1 << 63) - 1))
    return F.conv(F.substring(F.md5(F.concat(k.cast("string"), hashed).cast("binary")), 1, 15), 16, 10).cast("long")


def unit_hash(elem: Column, k: Column, family: str = "xxhash64", seed: int = 0) -> Column:
    return slot_hash(element_hash(elem, family, seed), k, family)


def register_unit(v: Column, family: str = "xxhash64") -> Column:
    return (v.cast("double") + 0.5) / F.lit(float(1 << BITS[family]))


def register_energy(v: Column, family: str = "xxhash64") -> Column:
    return -F.log1p(-register_unit(v, family))


def _rotated(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def mixed_long(x: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """xxHash64 of 8-byte integers under given seeds (both uint64, broadcast against each other)."""
    one, two, three, four, five = PRIMES
    with np.errstate(over="ignore"):
        out = (seed + five + np.uint64(8)) ^ (_rotated(x * two, 31) * one)
        out = _rotated(out, 27) * one + four
        out = (out ^ (out >> np.uint64(33))) * two
        out = (out ^ (out >> np.uint64(29))) * three
    return out ^ (out >> np.uint64(32))


def slot_seeds(m: int) -> np.ndarray:
    """State of Spark's xxhash64 after each function index 0 .. m-1."""
    return mixed_long(np.arange(m, dtype=np.uint64), SPARK_SEED)
