"""The book of registered queries and the SQL that gives the same rows in another engine."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None, name: str | None = None):
    """Register a function (spark, sf_dir) -> DataFrame under its own or a given name, with its SQL if there is any."""

    def keep(f):
        QUERIES[name or f.__name__] = f
        if oracle:
            ORACLES[name or f.__name__] = oracle
        return f

    return keep


def rounded(df: DataFrame, cols: list[str], keys: list[str] | tuple = (), digits: int = 3) -> DataFrame:
    return df.select(*keys, *[F.round(c, digits).alias(c) for c in cols])


def within(estimate: Column, exact: Column, std_err: Column, sigmas: float = 4.0, slack: float = 1.0) -> Column:
    """Whether an estimate lies within so many standard errors of the exact value (and one element)."""
    return F.abs(estimate - exact) <= sigmas * std_err + slack
