"""Toxicity by a factorization machine over hashed terms.

A text's terms (lower-case words without edge punctuation, and the heads of long words) hash to 2^16 slots; the score is a bias, the slots'
linear weights, and the inner products of their factor vectors over all pairs, computed in linear time. Weights
come from at most MAX_ROWS labelled rows whose crc32(doc_id as text) mod 5 is not 0 (a documented bound; rows are
chosen by a hash of doc_id); training runs in the driver with adaptive gradient steps, scoring map side. A fifth of the
training rows is kept from the gradient steps and gives the scale and shift that turn margins into probabilities.

Defined cases: null or empty text scores the bias; null labels are not learned from; repeated label rows count
once per document (the larger), and of repeated documents the least text is learned from; repeated documents each get a
row; a null doc_id is scored and not held out; without labels, or with one class alone, every margin is -2 or 2 (scores
.119 or .881); other columns are not read.
"""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setoverlap.llm.common import id_and_text, map_rows

SLOTS, FACTORS = 1 << 16, 4
MAX_ROWS = 20_000
LEAST_DOCS = 5
#: A slot seen in so many rows has a factor vector, whatever it tells by itself.
PAIR_DOCS = 30
#: Penalties on a linear weight and on a factor vector: a slot that no row needs goes to zero.
SPARSE_W, SPARSE_V = 1e-3, 1e-3
#: One training row in so many calibrates.
CALIBRATE = 5
HEADS = (5, 7)
STRIP = ".,;:!?\"'()[]{}*%$&#|<>-_"


def terms_of(word: str) -> list[str]:
    """A word without edge punctuation, and its heads of 5 and 7 characters (inflected and compound forms)."""
    w = word.strip(STRIP)
    return [w, *(f"^{w[:k]}" for k in HEADS if len(w) > k)]


def slots_of(text: str, cache: dict[str, tuple[int, ...]]) -> list[int]:
    """Distinct slots of a text's terms, in order."""
    found: set[int] = set()
    for w in set(text.lower().split()):
        s = cache.get(w)
        if s is None:
            s = tuple(zlib.crc32(t.encode("utf-8", "surrogatepass")) % SLOTS for t in terms_of(w))
            if len(cache) < 300_000 and len(w) < 40:
                cache[w] = s
        found.update(s)
    return sorted(found)


class FactorizationMachine:
    """margin: scale * (bias + weights + pairs) + shift; scale and shift come from calibration."""

    def __init__(self, bias: float, w: np.ndarray, v: np.ndarray, scale: float = 1.0, shift: float = 0.0):
        self.bias, self.w, self.v, self.scale, self.shift = bias, w, v, scale, shift

    def margin(self, slots: list[int]) -> float:
        return self.scale * self.raw(slots) + self.shift

    def raw(self, slots: list[int]) -> float:
        at = np.asarray(slots, np.int64)
        if not len(at):
            return float(self.bias)
        v = self.v[at]
        total = v.sum(0)
        return float(self.bias + self.w[at].sum() + 0.5 * ((total * total).sum() - (v * v).sum()))

    def probability(self, slots: list[int]) -> float:
        return 1.0 / (1.0 + float(np.exp(-min(35.0, max(-35.0, self.margin(slots))))))


def fit(rows: list, labels: list[int], epochs: int = 12, batch: int = 64, rate: float = 0.1, l2: float = 2e-4, seed: int = 7, sparse_w: float = SPARSE_W, sparse_v: float = SPARSE_V, pair_docs: int = PAIR_DOCS) -> FactorizationMachine:
    """Adaptive gradient descent on the log loss over rows of slots (lists or arrays). Every slot of LEAST_DOCS rows has a
    linear weight and every slot of PAIR_DOCS rows a factor vector; penalties, not tests of single slots, make both sparse."""
    y = np.asarray(labels, np.float64)
    w, r = np.zeros(SLOTS), np.random.default_rng(seed)
    v = np.zeros((SLOTS, FACTORS))
    if not len(y) or y.min() == y.max():
        return FactorizationMachine(-2.0 if not len(y) or y.max() == 0 else 2.0, w, v)
    seen = np.zeros(SLOTS, np.int64)
    for x in rows:
        seen[np.asarray(x, np.int64)] += 1  # distinct within a row
    usable, paired = seen >= LEAST_DOCS, seen >= pair_docs
    kept = [at[usable[at]].astype(np.uint16) for at in (np.asarray(x, np.int64) for x in rows)]
    v[paired] = r.normal(0, 0.01, (int(paired.sum()), FACTORS))
    bias, gw, gv, gb = float(np.log(y.mean() / (1 - y.mean()))), np.full(SLOTS, 1e-6), np.full((SLOTS, FACTORS), 1e-6), 1e-6
    for _ in range(epochs):
        order = r.permutation(len(y))
        for start in range(0, len(order), batch):
            ids = [i for i in order[start : start + batch] if len(kept[i])]
            if not ids:
                continue
            at, sizes = np.concatenate([kept[i] for i in ids]), [len(kept[i]) for i in ids]
            begins, doc = np.cumsum([0, *sizes[:-1]]), np.repeat(np.arange(len(ids)), sizes)
            vx = v[at]
            total = np.add.reduceat(vx, begins)
            m = bias + np.add.reduceat(w[at], begins) + 0.5 * ((total * total).sum(1) - np.add.reduceat((vx * vx).sum(1), begins))
            d = (1 / (1 + np.exp(-np.clip(m, -35, 35))) - y[ids]) / len(ids)
            slots, back = np.unique(at, return_inverse=True)
            dw = np.bincount(back, d[doc], len(slots)) + l2 * w[slots]
            dv = np.stack([np.bincount(back, d[doc] * (total[doc, k] - vx[:, k]), len(slots)) for k in range(FACTORS)], 1) + l2 * v[slots]
            dv[~paired[slots]] = 0.0
            gw[slots] += dw * dw
            gv[slots] += dv * dv
            gb += float(d.sum()) ** 2
            step = rate / np.sqrt(gw[slots])
            new = w[slots] - step * dw
            w[slots] = np.sign(new) * np.maximum(0.0, np.abs(new) - sparse_w * step)
            new = v[slots] - 0.3 * rate * dv / np.sqrt(gv[slots])
            norm, limit = np.sqrt((new * new).sum(1)), sparse_v * rate / np.sqrt(gv[slots].sum(1))
            v[slots] = new * np.maximum(0.0, 1 - limit / np.maximum(norm, 1e-12))[:, None]
            bias -= rate * float(d.sum()) / np.sqrt(gb)
    return FactorizationMachine(bias, w.astype(np.float32), v.astype(np.float32))


def fit_calibrated(rows: list, labels: list[int]) -> FactorizationMachine:
    """Fit on four fifths of the rows; logistic regression of the other fifth's labels on their margins sets scale and shift."""
    out = [i % CALIBRATE == CALIBRATE - 1 for i in range(len(rows))]
    model = fit([x for x, o in zip(rows, out, strict=True) if not o], [t for t, o in zip(labels, out, strict=True) if not o])
    z = np.array([model.raw(x) for x, o in zip(rows, out, strict=True) if o])
    y = np.array([t for t, o in zip(labels, out, strict=True) if o], np.float64)
    if not len(y) or y.min() == y.max() or not model.w.any() and not model.v.any():
        return model
    want = np.where(y == 1, (y.sum() + 1) / (y.sum() + 2), 1 / (len(y) - y.sum() + 2))
    at = np.array([1.0, 0.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(at[0] * z + at[1], -35, 35)))
        c = p * (1 - p) + 1e-9
        slope = np.array([((p - want) * z).sum(), (p - want).sum()])
        curve = np.array([[(c * z * z).sum() + 1e-6, (c * z).sum()], [(c * z).sum(), c.sum() + 1e-6]])
        at = at - np.clip(np.linalg.solve(curve, slope), -2, 2)
    if at[0] > 0:
        model.scale, model.shift = float(at[0]), float(at[1])
    return model


def fold(doc_id):
    return F.crc32(doc_id.cast("string").cast("binary")) % 5


def train(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS) -> FactorizationMachine:
    chosen = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").cast("int").alias("y"))
    chosen = chosen.where(fold(F.col("doc_id")) != 0).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    texts = id_and_text(docs).join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "y").agg(F.min("text").alias("text"))  # at most max_rows ids

    def setup():
        cache: dict[str, tuple[int, ...]] = {}
        return lambda i, t: (i, np.asarray(slots_of(t, cache), np.uint16).tobytes())

    # row and label cross together: the id column carries (doc_id, label) folded as 2 * doc_id + label
    coded = texts.select((F.col("doc_id") * 2 + F.col("y")).alias("doc_id"), "text")
    # two bytes a slot keep the driver's share small: at most max_rows documents' distinct slots
    got = [(r["code"], np.frombuffer(r["slots"], np.uint16)) for r in map_rows(coded, setup, "code long, slots binary").collect()]
    got.sort(key=lambda x: (zlib.crc32(str(x[0] >> 1).encode()), x[0]))  # an order that ids do not follow
    return fit_calibrated([x for _, x in got], [code & 1 for code, _ in got])


def toxicity(docs: DataFrame, labels: DataFrame, model: FactorizationMachine | None = None) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    model = model or train(docs, labels)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def setup():
        fm, cache = shared.value, {}

        def row(i, text):
            p = fm.probability(slots_of(text, cache))
            return i, p, int(p >= 0.5)

        return row

    got = map_rows(id_and_text(docs), setup, "doc_id long, score double, predicted int")
    return got.select("doc_id", F.coalesce(fold(F.col("doc_id")) == 0, F.lit(False)).alias("held_out"), "score", "predicted")
