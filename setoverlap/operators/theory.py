"""Laws, information bound and asymptotic variances, as column arithmetic over set sizes a, b, n and m registers.

`variant` tells printed formulas from those that follow from the model when every size comes from one set of
registers ("shared", "direct"); simulations agree with the latter (see README).
"""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


def _parts(a, b, n):
    return a + b - n, a - n, b - n


def case_probabilities(a: Column, b: Column, n: Column) -> Column:
    u, p, q = _parts(a, b, n)
    return F.struct((n / u).alias("p_tie"), (q / u).alias("p_b"), (p / u).alias("p_a"))


def fisher_matrix(a: Column, b: Column, n: Column, m: Column) -> Column:
    """Entries of the information matrix of (a, b, n); (a, b) is 0. Terms of an empty part vanish."""
    u, p, q = _parts(a, b, n)
    inv = lambda x: F.coalesce(F.try_divide(F.lit(1.0), x), F.lit(0.0))
    s = m / u
    return F.struct((s * (q / (a * a) + inv(p))).alias("aa"), (s * (p / (b * b) + inv(q))).alias("bb"), (s * (inv(n) + inv(p) + inv(q))).alias("nn"), (-s * inv(p)).alias("an"), (-s * inv(q)).alias("bn"))


def crb_intersection(a: Column, b: Column, n: Column, m: Column) -> Column:
    """Smallest variance of an unbiased estimate of n: (u/m) / (1/n + q/(a^2+pq) + p/(b^2+pq)); 0 at n = 0."""
    u, p, q = _parts(a, b, n)
    return F.when(n > 0, (u / m) / (F.try_divide(F.lit(1.0), n) + q / (a * a + p * q) + p / (b * b + p * q))).otherwise(0.0)


def crb_from_fisher(a: Column, b: Column, n: Column, m: Column) -> Column:
    """The same bound as entry (n, n) of the inverse information matrix, for p, q, n > 0."""
    f = fisher_matrix(a, b, n, m)
    return F.lit(1.0) / (f["nn"] - f["an"] * f["an"] / f["aa"] - f["bn"] * f["bn"] / f["bb"])


def var_scheme1(a: Column, b: Column, n: Column, m: Column, variant: str = "direct") -> Column:
    """Inclusion-exclusion. direct: covariances a^2/m, b^2/m of a size with its union; printed: those of a fitted n."""
    u, p, q = _parts(a, b, n)
    if variant == "direct":
        return (u * u - a * a - b * b + 2 * n * a * b / u) / m
    cov_a, cov_b = cov_card_union(a, b, n, m, "printed"), cov_card_union(b, a, n, m, "printed")
    return (a * a + b * b + u * u + 2 * n * a * b / u) / m - 2 * (cov_a + cov_b)


def var_scheme2(a: Column, b: Column, n: Column, m: Column) -> Column:
    u, _, _ = _parts(a, b, n)
    return n * u / m


def var_scheme3(a: Column, b: Column, n: Column, m: Column, variant: str = "shared") -> Column:
    """Jaccard ratio times the sum. lemma: independent sketches; shared: same registers; printed: as stated."""
    u, p, q = _parts(a, b, n)
    s, j, n = a + b, n / u, F.nullif(n, F.lit(0.0))
    if variant == "printed":
        return n * n / m * (1 + 2 * a * b / (u * s) + (p + q) * u * u / (n * s * s))
    norm = (a * a + b * b + 2 * a * b * j) / (s * s) + (p + q) * u * u / (n * s * s)
    if variant == "shared":
        norm = norm + 2 * (a * q + b * p) / (s * s)
    return n * n * norm / m


def delta_variance(var: Column, slope: Column) -> Column:
    return var * slope * slope


def product_variance(mx: Column, vx: Column, my: Column, vy: Column, cov: Column | float = 0.0) -> Column:
    """First-order variance of a product; the covariance term is 0 for independent factors."""
    return mx * mx * vy + my * my * vx + 2 * mx * my * cov


def jaccard_variance(j: Column, m: Column) -> Column:
    return j * (1 - j) / m


def var_jaccard_ratio(j: Column, m: Column) -> Column:
    """Variance of J / (1 + J)."""
    return delta_variance(jaccard_variance(j, m), 1 / ((1 + j) * (1 + j)))


def var_card_sum(a: Column, b: Column, n: Column, m: Column) -> Column:
    u, _, _ = _parts(a, b, n)
    return (a * a + b * b + 2 * a * b * n / u) / m


def cov_card_card(a: Column, b: Column, n: Column, m: Column) -> Column:
    u, _, _ = _parts(a, b, n)
    return n * a * b / (m * u)


def cov_card_union(a: Column, b: Column, n: Column, m: Column, variant: str = "direct") -> Column:
    """Covariance of a set's size with its union's."""
    if variant == "direct":
        return a * a / m
    u, p, q = _parts(a, b, n)
    return (a * a + n * a * b / u) / m - crb_intersection(a, b, n, m) * a * a / (a * a + p * q)


def max_hash_pdf(x: Column, c: Column) -> Column:
    return c * F.pow(x, c - 1)


def max_hash_cdf(x: Column, c: Column) -> Column:
    return F.pow(x, c)


def max_hash_mean(c: Column) -> Column:
    return c / (c + 1)


def max_hash_var(c: Column) -> Column:
    return c / ((c + 1) * (c + 1) * (c + 2))


def beta_pdf(x: pd.Series, s: float, t: float) -> pd.Series:
    """General beta density, for checks of the identities it obeys."""
    const = math.lgamma(s + t) - math.lgamma(s) - math.lgamma(t)
    return x.map(lambda v: math.exp(const + (s - 1) * math.log(v) + (t - 1) * math.log1p(-v)))


def log_gamma(x: pd.Series) -> pd.Series:
    return x.map(math.lgamma)


def beta_pdf_column(x: Column, s: Column, t: Column) -> Column:
    """General beta density; the log-gamma function alone leaves the JVM, in Arrow batches."""
    lg = F.pandas_udf(log_gamma, DoubleType())
    const = lg(s + t) - lg(s) - lg(t)
    return F.exp(const + (s - 1) * F.ln(x) + (t - 1) * F.log1p(-x))


def beta_cdf(x: float, s: float, t: float, steps: int = 4000) -> float:
    """By the midpoint rule."""
    return float(beta_pdf(pd.Series([(i + 0.5) * x / steps for i in range(steps)]), s, t).sum() * x / steps)
