"""The methods as SQL: scalar functions, table functions and an aggregate that `register` adds to a session.

Scalars are SQL functions (their bodies are inlined by the optimizer, no Python); the table functions and the aggregate
run in Arrow batches or once a call.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

#: name: (arguments, result type, body)
SCALARS = {
    "intersection_bound": ("a DOUBLE, b DOUBLE, n DOUBLE, m DOUBLE", "DOUBLE", "CASE WHEN n > 0 THEN ((a + b - n) / m) / (1 / n + (b - n) / (a * a + (a - n) * (b - n)) + (a - n) / (b * b + (a - n) * (b - n))) ELSE 0D END"),
    "jaccard_of": ("a DOUBLE, b DOUBLE, n DOUBLE", "DOUBLE", "try_divide(n, a + b - n)"),
    "scheme_inclusion_exclusion": ("a DOUBLE, b DOUBLE, u DOUBLE", "DOUBLE", "a + b - u"),
    "scheme_jaccard_union": ("j DOUBLE, u DOUBLE", "DOUBLE", "j * u"),
    "scheme_jaccard_sum": ("j DOUBLE, a DOUBLE, b DOUBLE", "DOUBLE", "j / (1 + j) * (a + b)"),
    "register_energy": ("v BIGINT", "DOUBLE", "-log1p(-((v + 0.5D) / 9223372036854775808D))"),
    "band_recall": ("j DOUBLE, r INT, m INT", "DOUBLE", "1 - pow(1 - pow(j, r), m / r)"),
}


class Shingles:
    """Runs of `width` words of a text, each once, with its first word."""

    def eval(self, text: str, width: int):
        words, seen = (text or "").lower().split(), set()
        for i in range(max(1, len(words) - width + 1) if words else 0):
            run = " ".join(words[i : i + width])
            if run not in seen:
                seen.add(run)
                yield run, i


class NewtonTrace:
    """One row an iteration of the maximum-likelihood fit from the interior start, for statistics without empty parts."""

    def eval(self, k_tie: int, k_b: int, k_a: int, sum_a: float, sum_b: float, sum_any: float, steps: int):
        a, b, n = (k_tie + k_a) / sum_any, (k_tie + k_b) / sum_any, k_tie / sum_any
        yield 0, a, b, n
        for i in range(steps):
            p, q = a - n, b - n
            wa, wb = k_a / p / p, k_b / q / q
            ga, gb, gn = k_b / a + k_a / p - sum_a, k_a / b + k_b / q - sum_b, k_tie / n - k_b / q - k_a / p + sum_any
            ha, hb = k_b / a / a + wa, k_a / b / b + wb
            dn = (gn + wa * ga / ha + wb * gb / hb) / (k_tie / n / n + wa + wb - wa * wa / ha - wb * wb / hb)
            da, db = (ga + wa * dn) / ha, (gb + wb * dn) / hb
            t = min([1.0] + [0.9 * x / -dx for x, dx in ((p, da - dn), (q, db - dn), (n, dn)) if x + dx <= 0])
            a, b, n = a + t * da, b + t * db, n + t * dn
            yield i + 1, a, b, n


def packed_registers(k: pd.Series, v: pd.Series) -> list[int]:
    """Grouped aggregate: the least v of each k, in order of k."""
    return v.groupby(k).min().sort_index().tolist()


def register(spark: SparkSession) -> None:
    """Temporary functions of this session; registering twice changes nothing."""
    for name, (args, kind, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("shingles", F.udtf(Shingles, returnType="shingle string, at int"))
    spark.udtf.register("newton_trace", F.udtf(NewtonTrace, returnType="iter int, card_a double, card_b double, card_both double"))
    spark.udf.register("register_pack", F.pandas_udf(packed_registers, "array<bigint>", F.PandasUDFType.GROUPED_AGG))
