"""Queries by name, with SQL of the same result for another engine where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    """Registers a function (spark, sf_dir) -> DataFrame under its own name."""

    def keep(function):
        QUERIES[function.__name__] = function
        if sql:
            ORACLES[function.__name__] = sql
        return function

    return keep


def r6(column: Column | str, name: str | None = None) -> Column:
    c = F.col(column) if isinstance(column, str) else column
    return F.round(c.cast("double"), 6).alias(name or (column if isinstance(column, str) else "x"))


def rounded(df: DataFrame) -> DataFrame:
    """All doubles to six places."""
    return df.select(*[F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])
