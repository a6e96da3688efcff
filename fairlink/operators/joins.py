"""Joins that the linkage needs beside the equi-join: band, as-of, interval, salted, counted."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def pair_counts(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    """Pairs per key from the sizes of both sides, without making the pairs."""
    left, right = a.groupBy(*keys).agg(F.count("*").alias("_a")), b.groupBy(*keys).agg(F.count("*").alias("_b"))
    return left.join(right, keys).select(*keys, (F.col("_a") * F.col("_b")).alias("pairs"))


def band(a: DataFrame, b: DataFrame, x: str, y: str, width: float) -> DataFrame:
    """Rows with |x - y| <= width: b goes to its bucket and both neighbours, the rest is an equi-join."""
    left = a.withColumn("_k", F.floor(F.col(x) / width).cast("long"))
    right = b.withColumn("_k", F.explode(F.sequence(F.floor(F.col(y) / width).cast("long") - 1, F.floor(F.col(y) / width).cast("long") + 1)))
    return left.join(right, "_k").where(F.abs(F.col(x) - F.col(y)) <= width).drop("_k")


def as_of(a: DataFrame, b: DataFrame, key: str, at: str, take: list[str]) -> DataFrame:
    """Each row of a with the last values of b at or before it: a union and one window, no range join."""
    left = a.withColumn("_b", F.lit(1))
    right = b.select(key, at, *take).withColumn("_b", F.lit(0))
    both = right.unionByName(left, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(at, "_b").rowsBetween(Window.unboundedPreceding, 0)
    filled = both.withColumns({f"_{c}": F.last(F.when(F.col("_b") == 0, F.col(c)), ignorenulls=True).over(w) for c in take})
    return filled.where("_b = 1").drop("_b", *take).withColumnsRenamed({f"_{c}": c for c in take})


def interval(a: DataFrame, b: DataFrame, key: str, start: str, time: str, seconds: int) -> DataFrame:
    """Rows of one key with start < time <= start + seconds, by buckets of that length."""
    micros = lambda c: F.unix_micros(c.cast("timestamp"))
    slot = lambda c: F.floor(micros(c) / (seconds * 1_000_000)).cast("long")
    left = a.withColumn("_s", F.explode(F.array(slot(F.col(start)), slot(F.col(start)) + 1)))
    right = b.withColumn("_s", slot(F.col(time)))
    inside = (F.col(time) > F.col(start)) & (micros(F.col(time)) <= micros(F.col(start)) + seconds * 1_000_000)
    return left.join(right, [key, "_s"]).where(inside).drop("_s")


def salted(big: DataFrame, small: DataFrame, key: str, spread: str, salts: int) -> DataFrame:
    """An equi-join whose hot keys are spread over `salts` tasks; the small side is repeated so often."""
    left = big.withColumn("_salt", F.pmod(F.xxhash64(spread), F.lit(salts)).cast("int"))
    right = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return left.join(right, [key, "_salt"]).drop("_salt")
