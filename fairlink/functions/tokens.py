"""Tokens of quasi-identifiers, as arrays of strings with the attribute's prefix."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def normalise(text: Column) -> Column:
    """Lower case, punctuation to nothing, outer white space off, null to empty."""
    return F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[.,;:'\"-]", ""))


def qgrams(text: Column, prefix: str, q: int = 2, pad: bool = False) -> Column:
    """Distinct substrings of q characters; a shorter text is one token, an empty one none."""
    value = normalise(text)
    if pad:
        value = F.when(value != "", F.concat(F.lit("_" * (q - 1)), value, F.lit("_" * (q - 1)))).otherwise(value)
    grams = F.transform(F.sequence(F.lit(1), F.length(value) - (q - 1)), lambda i: F.concat(F.lit(prefix), F.substr(value, i, F.lit(q))))
    none = F.array().cast("array<string>")
    return F.when(value == "", none).when(F.length(value) < q, F.array(F.concat(F.lit(prefix), value))).otherwise(F.array_distinct(grams))


def exact(value: Column, prefix: str) -> Column:
    """The whole value as one token; null has none."""
    return F.when(value.isNull(), F.array().cast("array<string>")).otherwise(F.array(F.concat(F.lit(prefix), value.cast("string"))))


def each(values: Column, prefix: str) -> Column:
    """One token per element of a multi-valued attribute."""
    return F.transform(F.coalesce(values, F.array().cast("array<string>")), lambda v: F.concat(F.lit(prefix), v))


def near(value: Column, prefix: str, step: float, width: int) -> Column:
    """Buckets around a number, so that near values share tokens."""
    at = F.floor(value / step).cast("long")
    return F.transform(F.sequence(at - width, at + width), lambda b: F.concat(F.lit(prefix), b.cast("string")))
