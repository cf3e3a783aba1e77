"""Byte-level BPE encoding and decoding by a two-tier lookup.

A minimal perfect hash (hash and displace) resolves a pre-token that is itself in the vocabulary: one probe and one
comparison. Any other pre-token is merged with a heap of (rank, place) over doubly linked bytes, n log n in its
length. Workers keep the ids of recent pre-tokens in a bounded cache. Decoding concatenates the bytes of the ids.

Defined cases: null text encodes as empty; repeated rows each get a row; an empty table gives an empty result;
other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import itertools
import struct
from array import array

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, LongType, StringType, StructField, StructType
from xxhash import xxh3_64_intdigest

from setoverlap.llm.common import id_and_text, map_rows, small_batches

CACHE_ROWS = 400_000
CACHE_CHARS = 64


def read_ranks(path: str) -> list[bytes]:
    """Token bytes in order of rank, which must be dense from 0."""
    with open(path, "rb") as f:
        pairs = [(int(b), base64.b64decode(a)) for a, b in map(bytes.split, filter(None, f.read().splitlines()))]
    pairs.sort()
    if [r for r, _ in pairs] != list(range(len(pairs))):
        raise ValueError("ranks are not dense")
    return [t for _, t in pairs]


class PerfectHash:
    """Minimal perfect hash of byte strings: every key has a slot of its own among exactly len(keys)."""

    PER_BUCKET = 2

    def __init__(self, keys: list[bytes]):
        self.n, self.n_buckets = len(keys), max(1, len(keys) // self.PER_BUCKET)
        self.shift, self.slots = array("i", bytes(4 * self.n_buckets)), array("i", [-1] * self.n)
        buckets: list[list[int]] = [[] for _ in range(self.n_buckets)]
        halves = [self._halves(k) for k in keys]
        for i, (a, _) in enumerate(halves):
            buckets[a % self.n_buckets].append(i)
        free = 0
        for b in sorted(range(self.n_buckets), key=lambda b: -len(buckets[b])):
            members = buckets[b]
            if not members:
                break
            if len(members) == 1:  # any free slot will do: its number is stored as -1 - slot
                while self.slots[free] >= 0:
                    free += 1
                self.shift[b], self.slots[free] = -1 - free, members[0]
                continue
            d = 0
            while True:
                places = [self._place(halves[i], d) for i in members]
                if len(set(places)) == len(places) and all(self.slots[p] < 0 for p in places):
                    break
                d += 1
            self.shift[b] = d
            for i, p in zip(members, places, strict=True):
                self.slots[p] = i

    @staticmethod
    def _halves(key: bytes) -> tuple[int, int]:
        h = xxh3_64_intdigest(key)
        return h & 0xFFFFFFFF, h >> 32

    def _place(self, halves: tuple[int, int], d: int) -> int:
        return (halves[1] + d * (halves[0] >> 8 | 1)) % self.n

    def index(self, key: bytes) -> int:
        """The key's number if it is in the set; for other keys some number, to be checked by the caller."""
        h = xxh3_64_intdigest(key)
        a = h & 0xFFFFFFFF
        d = self.shift[a % self.n_buckets]
        return self.slots[-1 - d if d < 0 else ((h >> 32) + d * (a >> 8 | 1)) % self.n]


class Encoder:
    def __init__(self, tokens: list[bytes], perfect: PerfectHash, pattern: str):
        import regex

        self.tokens, self.perfect, self.pattern = tokens, perfect, regex.compile(pattern)
        self.ranks = {t: i for i, t in enumerate(tokens)}
        self.single = [self.ranks[bytes([b])] for b in range(256)]
        self.cache: dict[str, bytes] = {}

    def rank(self, piece: bytes) -> int:
        i = self.perfect.index(piece)
        return i if self.tokens[i] == piece else -1

    def merge(self, piece: bytes) -> list[int]:
        """Ranks after merging the lowest-ranked neighbours first, the left one on ties."""
        n, get, push, pop = len(piece), self.ranks.get, heapq.heappush, heapq.heappop
        ids = [self.single[b] for b in piece]
        right, left = list(range(1, n + 2)), list(range(-1, n))
        # an entry is one integer: rank, start, end, so that ranks compare first and places next
        heap = [r << 64 | i << 32 | i + 2 for i in range(n - 1) if (r := get(piece[i : i + 2])) is not None]
        heapq.heapify(heap)
        while heap:
            top = pop(heap)
            end, i = top & 0xFFFFFFFF, top >> 32 & 0xFFFFFFFF
            j = right[i]
            if ids[i] < 0 or j >= n or right[j] != end:
                continue  # one of the two was merged meanwhile
            ids[i], ids[j], right[i], left[end] = top >> 64, -1, end, i
            if end < n:
                e = right[end]
                if (r := get(piece[i:e])) is not None:
                    push(heap, r << 64 | i << 32 | e)
            k = left[i]
            if k >= 0 and (r := get(piece[k:end])) is not None:
                push(heap, r << 64 | k << 32 | end)
        return [x for x in ids if x >= 0]

    def packed(self, unit: str) -> bytes:
        """The ids of one pre-token as little-endian unsigned 32-bit integers."""
        raw = unit.encode("utf-8", "surrogatepass")
        r = self.rank(raw)
        ids = [r] if r >= 0 else self.merge(raw)
        out = struct.pack(f"<{len(ids)}I", *ids)
        if len(unit) <= CACHE_CHARS:
            if len(self.cache) >= CACHE_ROWS:
                self.cache.clear()
            self.cache[unit] = out
        return out

    def encode(self, text: str) -> bytes:
        get, miss = self.cache.get, self.packed
        return b"".join([get(u) or miss(u) for u in self.pattern.findall(text)])

    def decode(self, packed: bytes) -> bytes:
        ids = array("I")
        ids.frombytes(packed)
        return b"".join(map(self.tokens.__getitem__, ids))


#: The encoder and its cache serve all tasks of a worker.
_WORKER: dict[tuple, Encoder] = {}


def shared_encoder(df: DataFrame, ranks_path: str, pattern: str):
    """A function for workers that gives the encoder of a broadcast vocabulary (its size is the vocabulary's)."""
    tokens = read_ranks(ranks_path)
    sent = df.sparkSession.sparkContext.broadcast((tokens, PerfectHash(tokens)))

    def encoder() -> Encoder:
        key = (hashlib.sha256(b"\0".join(sent.value[0])).digest(), pattern)
        if key not in _WORKER:
            _WORKER.clear()
            _WORKER[key] = Encoder(*sent.value, pattern)
        return _WORKER[key]

    return encoder


def encode_decode(df: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256."""
    encoder = shared_encoder(df, ranks_path, pattern)

    def setup():
        e = encoder()

        def row(i, text):
            packed = e.encode(text)
            return i, len(packed) // 4, hashlib.sha256(packed).hexdigest(), hashlib.sha256(e.decode(packed)).hexdigest()

        return row

    return map_rows(id_and_text(df), setup, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode_ids(df: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """doc_id and ids (array of integers): the operator's real output."""
    encoder = shared_encoder(df, ranks_path, pattern)

    def setup():
        e = encoder()

        def row(i, text):
            ids = array("I")
            ids.frombytes(e.encode(text))
            return i, ids.tolist()

        return row

    return map_rows(id_and_text(df), setup, "doc_id long, ids array<int>")


def tokenised(df: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """All columns of df but text, then n_tokens, ids, ids_sha256 and decoded_sha256 (replacing columns of these names)."""
    encoder = shared_encoder(df, ranks_path, pattern)
    new = {"n_tokens": LongType(), "ids": ArrayType(IntegerType()), "ids_sha256": StringType(), "decoded_sha256": StringType()}
    names = [c for c in df.columns if c != "text" and c not in new]
    rows = df.select(F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), F.struct(F.lit(0).alias("_"), *[F.col(f"`{c}`") for c in names]).alias("others"))

    def run(batches):
        e = encoder()
        for batch in batches:
            packed = [e.encode(t) for t in batch.column(0).to_pylist()]
            flat = pa.Array.from_buffers(pa.int32(), sum(map(len, packed)) // 4, [None, pa.py_buffer(b"".join(packed))])
            ends = pa.array(itertools.accumulate((len(p) // 4 for p in packed), initial=0), pa.int32())
            sha = lambda x: hashlib.sha256(x).hexdigest()
            yield pa.RecordBatch.from_arrays([
                batch.column(1), pa.array([len(p) // 4 for p in packed], pa.int64()), pa.ListArray.from_arrays(ends, flat),
                pa.array(map(sha, packed), pa.string()), pa.array((sha(e.decode(p)) for p in packed), pa.string()),
            ], ["others", *new])

    small_batches(df.sparkSession)
    schema = StructType([rows.schema["others"], *[StructField(c, k) for c, k in new.items()]])
    return rows.mapInArrow(run, schema).select(*[F.col(f"others.`{c}`").alias(c) for c in names], *new)
