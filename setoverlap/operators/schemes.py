"""The three baseline schemes and all estimators side by side, on the same registers by default."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setoverlap.operators.cardinality import card_from_registers
from setoverlap.operators.mle import mle_intersection
from setoverlap.operators.pairstats import jaccard_estimate

SCHEMES = ("inclusion_exclusion", "jaccard_union", "jaccard_sum", "ml")


def with_cardinalities(stats: DataFrame) -> DataFrame:
    """Adds c_a, c_b, c_any from the registers unless the caller joined others of its choice (HLL, native, exact)."""
    m = F.col("m")
    add = {k: card_from_registers(F.col(s), m) * F.col("scale") for k, s in (("c_a", "sum_a"), ("c_b", "sum_b"), ("c_any", "sum_any")) if k not in stats.columns}
    return stats.withColumns(add) if add else stats


def scheme_incl_excl(clip: bool = False) -> Column:
    n = F.col("c_a") + F.col("c_b") - F.col("c_any")
    return F.greatest(F.lit(0.0), F.least(n, F.col("c_a"), F.col("c_b"))) if clip else n


def scheme_jaccard_union() -> Column:
    return F.coalesce(jaccard_estimate(), F.lit(0.0)) * F.col("c_any")


def scheme_jaccard_sum() -> Column:
    j = F.coalesce(jaccard_estimate(), F.lit(0.0))
    return j / (1 + j) * (F.col("c_a") + F.col("c_b"))


def estimate_wide(stats: DataFrame, **ml) -> DataFrame:
    got = with_cardinalities(stats)
    got = got.withColumns({"inclusion_exclusion": scheme_incl_excl(), "jaccard_union": scheme_jaccard_union(), "jaccard_sum": scheme_jaccard_sum()})
    return mle_intersection(got, **ml).withColumn("ml", F.col("card_both"))


def estimate_all(stats: DataFrame, keys: list[str] | tuple = (), **ml) -> DataFrame:
    """(keys..., scheme, estimate), one row a scheme."""
    wide = estimate_wide(stats, **ml)
    rows = F.explode(F.array(*[F.struct(F.lit(s).alias("scheme"), F.col(s).alias("estimate")) for s in SCHEMES]))
    return wide.select(*keys, rows.alias("r")).select(*keys, "r.scheme", "r.estimate")
