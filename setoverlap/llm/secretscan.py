"""Secret scans by two character Markov models compared by log-likelihood ratio.

Base patterns find assignments, access keys and long hexadecimal runs. Beside them, every token of 16 or more
characters from the key alphabet is scored: bigrams of random strings against bigrams of ordinary identifiers. Both models are
trained from labelled samples drawn by a seeded generator: random strings over four alphabets, and identifiers
made of the corpus's own words (class counts of all documents, at most ALPHABET^2 rows) joined as programmers do.

Defined cases: null text reads as empty (no spans); repeated rows each get a row; an empty table gives an empty
result; other columns are not read. Offsets are code points, ends exclusive.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setoverlap.llm.common import id_and_text, map_rows, small_batches, spans_digest

KINDS = ["assign", "access", "hex", "random"]
# The contract's patterns; a run of fewer characters than allowed is dropped after the match.
ASSIGN = re.compile(r"""(?ai:(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?)([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
TOKEN = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_-]{16,}+={0,2}+(?![A-Za-z0-9+/_=-])")
CHARS = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_-="
ALPHABET = len(CHARS) + 1
CODE = {c: i for i, c in enumerate(CHARS)}
SAMPLES, SEED = 4000, 20240101
#: Mean log-likelihood ratio per character above which a token counts as random: 0 is where both models are equally likely (on samples held out of training, random strings score above 0.1, identifiers below -0.9).
THRESHOLD = 0.0

_CLASS = bytes(CODE.get(chr(b), ALPHABET - 1) for b in range(256))


def bigrams(strings) -> Counter:
    found: Counter = Counter()
    for s in strings:
        codes = [ALPHABET - 1, *(CODE.get(c, ALPHABET - 1) for c in s)]
        found.update(a * ALPHABET + b for a, b in zip(codes, codes[1:], strict=False))
    return found


def random_samples(n: int = SAMPLES, seed: int = SEED) -> list[str]:
    r = random.Random(seed)
    kinds = ["0123456789abcdef", CHARS[:62], CHARS[:64], CHARS[26:62]]
    return ["".join(r.choices(r.choice(kinds), k=r.randint(16, 48))) for _ in range(n)]


def corpus_bigrams(df: DataFrame) -> dict[int, int]:
    """Bigram counts of letters in the words of all documents: partial counts map side, at most ALPHABET^2 rows to the driver."""

    def run(batches):
        import numpy as np

        table = np.frombuffer(_CLASS, np.uint8)
        total = np.zeros(ALPHABET * ALPHABET, np.int64)
        for batch in batches:
            data = table[np.frombuffer(" ".join(batch.column(1).to_pylist()).encode("utf-8", "surrogatepass"), np.uint8)].astype(np.int32)
            total += np.bincount(data[:-1] * ALPHABET + data[1:], minlength=len(total))
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["pair", "n"])

    small_batches(df.sparkSession)
    rows = id_and_text(df).mapInArrow(run, "pair long, n long").groupBy("pair").agg(F.sum("n").alias("n")).collect()
    return {r["pair"]: r["n"] for r in rows}


class MarkovPair:
    """log P(random) - log P(ordinary) for each bigram, add-one smoothed."""

    def __init__(self, rand: dict[int, int], ordinary: dict[int, int]):
        a, b = self._logs(rand), self._logs(ordinary)
        self.ratio = [x - y for x, y in zip(a, b, strict=True)]

    @staticmethod
    def _logs(counts: dict[int, int]) -> list[float]:
        out = []
        for a in range(ALPHABET):
            row = [counts.get(a * ALPHABET + b, 0) + 1.0 for b in range(ALPHABET)]
            total = sum(row)
            out += [math.log(x / total) for x in row]
        return out

    def score(self, s: str) -> float:
        """Mean ratio per character; 0 for an empty string."""
        codes = [ALPHABET - 1, *(CODE.get(c, ALPHABET - 1) for c in s)]
        return sum(self.ratio[a * ALPHABET + b] for a, b in zip(codes, codes[1:], strict=False)) / max(1, len(s))


def identifier_samples(ordinary: dict[int, int], n: int = SAMPLES, seed: int = SEED) -> list[str]:
    """Identifiers whose words follow the corpus's bigrams, joined by case, underscores, hyphens and short numbers."""
    r, out = random.Random(seed + 1), []
    edge = ALPHABET - 1
    rows = [[ordinary.get(a * ALPHABET + b, 0) * (b < 26) for b in range(ALPHABET)] for a in range(ALPHABET)]

    def word() -> str:
        a, s = edge, ""
        for _ in range(r.randint(3, 9)):
            if not any(rows[a]):
                break
            a = r.choices(range(ALPHABET), rows[a])[0]
            s += CHARS[a]
        return s or "name"

    for _ in range(n):
        words = [word() for _ in range(r.randint(2, 4))]
        style = r.randrange(3)
        out.append(("_".join(words), "-".join(words), words[0] + "".join(w.capitalize() for w in words[1:]))[style] + r.choice(["", "", str(r.randrange(100)), f"_{r.randrange(10)}"]))
    return out


def train(df: DataFrame) -> MarkovPair:
    ordinary = corpus_bigrams(df)
    return MarkovPair(bigrams(random_samples()), dict(bigrams(identifier_samples(ordinary))))


def base_spans(text: str) -> list[tuple[int, int, str, int]]:
    out = [(m.start(), 0, "assign", m.end()) for m in ASSIGN.finditer(text) if m.end() - m.start(1) >= 12]
    if "AKIA" in text:
        out += [(m.start(), 1, "access", m.end()) for m in ACCESS.finditer(text)]
    return out + [(m.start(), 2, "hex", m.end()) for m in HEX.finditer(text)]


def added_spans(text: str, model: MarkovPair, base: list, threshold: float = THRESHOLD) -> list[tuple[int, int, str, int]]:
    """Random-looking tokens with letters that touch no base span."""
    out, at, sure = [], 0, sorted((s, e) for s, _, _, e in base)
    for m in TOKEN.finditer(text):
        s, e, v = m.start(), m.end(), m.group()
        while at < len(sure) and sure[at][1] <= s:
            at += 1
        if any(a < e for a, _ in sure[at : at + 1]) or not any(c.isalpha() for c in v):
            continue
        if model.score(v) >= threshold:
            out.append((s, 3, "random", e))
    return out


def secrets(df: DataFrame, model: MarkovPair | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_random."""
    model = model or train(df)
    shared = df.sparkSession.sparkContext.broadcast(model)

    def setup():
        pair = shared.value

        def row(i, text):
            base = base_spans(text)
            more = added_spans(text, pair, base, threshold)
            n = Counter(k for _, _, k, _ in base)
            return i, n["assign"], n["access"], n["hex"], hashlib.sha256(spans_digest(base).encode()).hexdigest(), spans_digest(base + more), len(more)

        return row

    return map_rows(id_and_text(df), setup, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_random long")
