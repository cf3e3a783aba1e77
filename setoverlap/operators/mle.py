"""Maximum-likelihood sizes (a, b, n) of two sets from the six sums of their sketches.

The log-likelihood is K1 ln n + K2 ln(q a) + K3 ln(p b) - a SA - b SB + n SU + const, p = a - n, q = b - n: a concave
function whose negative Hessian is an arrow matrix, so a Newton step needs three divisions. The iteration is a fold
inside the row: no user function, no driver loop, no job per step. Sketches of a boundary (no ties, one set inside
the other, equal sets, empty sides) have closed forms.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from setoverlap.operators.theory import crb_intersection

D = "double"


def _c(name: str) -> Column:
    return F.col(name).cast(D)


def log_likelihood(a: Column, b: Column, n: Column) -> Column:
    """Up to the constant that depends on the data alone; 0 ln 0 counts as 0."""
    xlogy = lambda k, y: F.when(k == 0, F.lit(0.0)).otherwise(k * F.ln(y))
    k1, k2, k3 = _c("k_tie"), _c("k_b"), _c("k_a")
    return xlogy(k1, n) + xlogy(k2, (b - n) * a) + xlogy(k3, (a - n) * b) - a * F.col("sum_a") - b * F.col("sum_b") + n * F.col("sum_any")


def case_density(xa: Column, xb: Column, a: Column, b: Column, n: Column) -> Column:
    """Density of the two maxima of one hash function: tie, A's smaller, A's larger."""
    u, p, q = a + b - n, a - n, b - n
    return F.when(xa == xb, n * F.pow(xa, u - 1)).when(xa < xb, q * a * F.pow(xb, q - 1) * F.pow(xa, a - 1)).otherwise(p * b * F.pow(xa, p - 1) * F.pow(xb, b - 1))


def score(a: Column, b: Column, n: Column) -> Column:
    k1, k2, k3, p, q = _c("k_tie"), _c("k_b"), _c("k_a"), a - n, b - n
    return F.struct((_c("k_b_seen") / a + k3 / p - F.col("sum_a")).alias("g_a"), (_c("k_a_seen") / b + k2 / q - F.col("sum_b")).alias("g_b"), (k1 / n - k2 / q - k3 / p + F.col("sum_any")).alias("g_n"))


def neg_hessian(a: Column, b: Column, n: Column) -> Column:
    k1, k2, k3, p, q = _c("k_tie"), _c("k_b"), _c("k_a"), a - n, b - n
    wa, wb = k3 / (p * p), k2 / (q * q)
    return F.struct((_c("k_b_seen") / (a * a) + wa).alias("aa"), (_c("k_a_seen") / (b * b) + wb).alias("bb"), (k1 / (n * n) + wa + wb).alias("nn"), (-wa).alias("an"), (-wb).alias("bn"))


def _let(value: Column, f) -> Column:
    """f(value) with value computed once: a one-element transform binds it."""
    return F.transform(F.array(value), f)[0]


def newton_step(a: Column, b: Column, n: Column, damping: float | None = 0.9) -> Column:
    """struct(a, b, n) after one step; damping keeps p, q, n above a tenth of their distance to 0."""
    g, h = score(a, b, n), neg_hessian(a, b, n)
    terms = F.struct(*[g[x].alias(x) for x in ("g_a", "g_b", "g_n")], *[h[x].alias(x) for x in ("aa", "bb", "nn", "an", "bn")])

    def solve(x: Column) -> Column:
        dn = (x["g_n"] - x["an"] * x["g_a"] / x["aa"] - x["bn"] * x["g_b"] / x["bb"]) / (x["nn"] - x["an"] * x["an"] / x["aa"] - x["bn"] * x["bn"] / x["bb"])
        return _let(dn, lambda d: F.struct(((x["g_a"] - x["an"] * d) / x["aa"]).alias("a"), ((x["g_b"] - x["bn"] * d) / x["bb"]).alias("b"), d.alias("n")))

    def move(x: Column) -> Column:
        if damping is None:
            return F.struct((a + x["a"]).alias("a"), (b + x["b"]).alias("b"), (n + x["n"]).alias("n"))
        room = lambda value, change: F.when(value + change > 0, F.lit(1.0)).otherwise(damping * value / -change)
        t = F.least(room(a - n, x["a"] - x["n"]), room(b - n, x["b"] - x["n"]), room(n, x["n"]))
        return _let(t, lambda t: F.struct((a + t * x["a"]).alias("a"), (b + t * x["b"]).alias("b"), (n + t * x["n"]).alias("n")))

    return _let(_let(terms, solve), move)


def initial(init: str = "interior") -> Column:
    """Start: interior splits the union's size by the case shares; scheme2 and scheme3 are the cheap estimates; given reads a0, b0, n0."""
    m, s = F.col("m").cast(D), F.struct
    seen = F.col("k_tie") + F.col("k_a") + F.col("k_b")
    union = seen / F.col("sum_any")
    share = lambda k: union * F.col(k) / seen
    a0, b0 = (m if init != "interior" else seen) / F.col("sum_a"), (m if init != "interior" else seen) / F.col("sum_b")
    n0 = {"interior": share("k_tie"), "scheme2": F.col("k_tie") / seen * union, "scheme3": F.col("k_tie") / (F.col("k_tie") + seen) * (a0 + b0), "given": F.col("n0") if init == "given" else None}[init]
    if init == "interior":
        return s((n0 + share("k_a")).alias("a"), (n0 + share("k_b")).alias("b"), n0.alias("n"))
    if init == "given":
        a0, b0 = F.col("a0"), F.col("b0")
    else:  # an estimate of n above either size is no feasible start
        n0 = F.least(n0, 0.999 * a0, 0.999 * b0)
    return s(a0.alias("a"), b0.alias("b"), n0.alias("n"))


def boundary() -> Column:
    """Name of the closed form that applies, or null for an interior maximum."""
    k1, k2, k3 = F.col("k_tie"), F.col("k_b"), F.col("k_a")
    none_a, none_b = (k1 + k3 + F.col("k_b_seen")) == 0, (k1 + k2 + F.col("k_a_seen")) == 0
    return F.when(none_a & none_b, "both_empty").when(none_a, "a_empty").when(none_b, "b_empty").when(k1 == 0, "disjoint").when((k2 == 0) & (k3 == 0), "identical").when(k3 == 0, "a_inside").when(k2 == 0, "b_inside")


def _closed() -> Column:
    part = lambda k, s: F.coalesce(F.try_divide(k, F.col(s)), F.lit(0.0))
    k1, k2, k3 = _c("k_tie"), _c("k_b"), _c("k_a")
    sa, sb, su = k1 + k3 + _c("k_b_seen"), k1 + k2 + _c("k_a_seen"), k1 + k2 + k3
    w, z = F.col("boundary"), F.lit(0.0)
    make = lambda a, b, n: F.struct(a.alias("a"), b.alias("b"), n.alias("n"))
    inner_a, inner_b, whole = part(sa, "sum_a"), part(sb, "sum_b"), part(su, "sum_any")
    return (
        F.when(w.isin("disjoint", "both_empty", "a_empty", "b_empty"), make(F.when(sa > 0, inner_a).otherwise(z), F.when(sb > 0, inner_b).otherwise(z), z))
        .when(w == "identical", make(whole, whole, whole))
        .when(w == "a_inside", make(inner_a, inner_a + part(k2, "sum_b"), inner_a))
        .when(w == "b_inside", make(inner_b + part(k3, "sum_a"), inner_b, inner_b))
    )


def fit_arrays(k_tie, k_b, k_a, k_b_seen, k_a_seen, sum_a, sum_b, sum_any, iters: int = 25, tol: float = 1e-12, damping: float = 0.9):
    """a, b, n, steps and whether each converged, for whole arrays of statistics at once: the fold's arithmetic from the
    interior start, and the closed forms at boundaries."""
    k1, k2, k3, sb_, sa_ = (np.asarray(x, np.float64) for x in (k_tie, k_b, k_a, k_b_seen, k_a_seen))
    ea, eb, eu = (np.asarray(x, np.float64) for x in (sum_a, sum_b, sum_any))
    with np.errstate(all="ignore"):
        in_a, in_b, all_ = k1 + k3 + sb_, k1 + k2 + sa_, k1 + k2 + k3
        inner_a, inner_b, whole = np.where(in_a > 0, in_a / ea, 0.0), np.where(in_b > 0, in_b / eb, 0.0), np.where(all_ > 0, all_ / eu, 0.0)
        apart = (in_a == 0) | (in_b == 0) | (k1 == 0)
        same, a_in, b_in = ~apart & (k2 == 0) & (k3 == 0), ~apart & (k3 == 0), ~apart & (k2 == 0)
        a = np.select([apart, same, a_in, b_in], [inner_a, whole, inner_a, inner_b + k3 / ea], (k1 + k3) / eu)
        b = np.select([apart, same, a_in, b_in], [inner_b, whole, inner_a + k2 / eb, inner_b], (k1 + k2) / eu)
        n = np.select([apart, same, a_in, b_in], [0.0, whole, inner_a, inner_b], k1 / eu)
        steps, done = np.zeros(len(a), np.int32), apart | same | a_in | b_in
        for _ in range(iters):
            at = np.flatnonzero(~done)
            if not len(at):
                break
            x, y, z, t1, t2, t3 = a[at], b[at], n[at], k1[at], k2[at], k3[at]
            p, q = x - z, y - z
            wa, wb = t3 / (p * p), t2 / (q * q)
            ga, gb, gn = sb_[at] / x + t3 / p - ea[at], sa_[at] / y + t2 / q - eb[at], t1 / z - t2 / q - t3 / p + eu[at]
            ha, hb = sb_[at] / (x * x) + wa, sa_[at] / (y * y) + wb
            dz = (gn + wa * ga / ha + wb * gb / hb) / (t1 / (z * z) + wa + wb - wa * wa / ha - wb * wb / hb)
            dx, dy = (ga + wa * dz) / ha, (gb + wb * dz) / hb
            step = np.ones(len(at))
            for value, change in ((p, dx - dz), (q, dy - dz), (z, dz)):
                step = np.minimum(step, np.where(value + change > 0, 1.0, damping * value / -change))
            a[at], b[at], n[at], steps[at] = x + step * dx, y + step * dy, z + step * dz, steps[at] + 1
            done[at] = np.abs(n[at] - z) <= tol * np.abs(n[at])
    return a, b, n, steps, done


def _fit_in_arrow(stats: DataFrame, iters: int, tol: float, damping: float) -> DataFrame:
    """Adds fit, struct(x struct(a, b, n), it, done), by `fit_arrays` over Arrow batches."""
    names = ["k_tie", "k_b", "k_a", "k_b_seen", "k_a_seen", "sum_a", "sum_b", "sum_any"]
    fit = StructType.fromDDL("fit struct<x: struct<a: double, b: double, n: double>, it: int, done: boolean>")

    def run(batches):
        for batch in batches:
            a, b, n, it, done = fit_arrays(*(batch.column(batch.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in names), iters, tol, damping)
            x = pa.StructArray.from_arrays([pa.array(a), pa.array(b), pa.array(n)], ["a", "b", "n"])
            out = pa.StructArray.from_arrays([x, pa.array(it), pa.array(done)], ["x", "it", "done"])
            yield pa.RecordBatch.from_arrays([*batch.columns, out], [*batch.schema.names, "fit"])

    return stats.mapInArrow(run, StructType([*stats.schema.fields, *fit.fields]))


def mle_intersection(stats: DataFrame, init: str = "interior", iters: int = 25, tol: float = 1e-12, damping: float | None = 0.9, engine: str = "sql") -> DataFrame:
    """Adds card_a, card_b, card_both, card_any, only_a, only_b, jaccard, iters, converged, boundary, var_hat.

    engine="arrow" takes the same steps from the interior start over whole batches in NumPy: for tens of millions of
    pairs, where an interpreted fold for each row would cost most of the run.
    """
    with_kind = stats.withColumn("boundary", boundary())
    if engine == "arrow":
        if init != "interior" or damping is None:
            raise ValueError("the arrow engine starts inside and takes damped steps")
        return _sized(_fit_in_arrow(with_kind, iters, tol, damping))
    start = F.struct(initial(init).alias("x"), F.lit(0).alias("it"), F.lit(False).alias("done"))

    def step(acc: Column, _: Column) -> Column:
        moved = newton_step(acc["x"]["a"], acc["x"]["b"], acc["x"]["n"], damping)
        close = lambda new: F.abs(new["n"] - acc["x"]["n"]) <= tol * F.abs(new["n"])
        after = _let(moved, lambda y: F.struct(y.alias("x"), (acc["it"] + 1).alias("it"), close(y).alias("done")))
        return F.when(acc["done"], acc).otherwise(after)

    fold = F.aggregate(F.sequence(F.lit(1), F.lit(iters)), start, step)
    solved = F.when(F.col("boundary").isNull(), fold).otherwise(F.struct(_closed().alias("x"), F.lit(0).alias("it"), F.lit(True).alias("done")))
    return _sized(with_kind.withColumn("fit", solved))


def _sized(got: DataFrame) -> DataFrame:
    """The columns that follow from a fit, in place of it."""
    sizes = {"card_a": F.col("fit.x.a") * F.col("scale"), "card_b": F.col("fit.x.b") * F.col("scale"), "card_both": F.col("fit.x.n") * F.col("scale")}
    got = got.withColumns(sizes | {"iters": F.col("fit.it"), "converged": F.col("fit.done")}).drop("fit")
    a, b, n = F.col("card_a"), F.col("card_b"), F.col("card_both")
    return got.withColumns({"card_any": a + b - n, "only_a": a - n, "only_b": b - n, "jaccard": F.try_divide(n, a + b - n), "var_hat": F.when(n > 0, crb_intersection(a, b, n, F.col("m").cast(D))).otherwise(0.0)})


def estimate_interval(est: DataFrame, z: float = 1.959963984540054) -> DataFrame:
    """Adds std_err, ci_lo, ci_hi: the bound at the estimate as its asymptotic variance."""
    se = F.sqrt("var_hat")
    return est.withColumns({"std_err": se, "ci_lo": F.greatest(F.col("card_both") - z * se, F.lit(0.0)), "ci_hi": F.col("card_both") + z * se})


def newton_trace(stats: DataFrame, init: str = "interior", iters: int = 8) -> DataFrame:
    """One row an iteration: the steps as unrolled projections."""
    cur = stats.withColumn("x0", initial(init))
    for i in range(iters):
        x = F.col(f"x{i}")
        cur = cur.withColumn(f"x{i + 1}", newton_step(x["a"], x["b"], x["n"]))
    rows = F.explode(F.array(*[F.struct(F.lit(i).alias("iter"), F.col(f"x{i}").alias("x")) for i in range(iters + 1)]))
    return cur.select(rows.alias("r")).select("r.iter", F.col("r.x.a").alias("card_a"), F.col("r.x.b").alias("card_b"), F.col("r.x.n").alias("card_both"))
