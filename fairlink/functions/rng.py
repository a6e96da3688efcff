"""Draws that are pure functions of keys, so that a retried task repeats its noise.

A draw depends on the seed, a purpose and a row's keys, never on partitions or row order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

DIGITS = 13
RANGE = float(1 << (4 * DIGITS))


def _key(seed: int, purpose: str, *columns: Column | str) -> Column:
    parts = [F.lit(f"{seed}|{purpose}"), *((F.col(c) if isinstance(c, str) else c).cast("string") for c in columns)]
    return F.concat_ws("|", *parts)


def whole(text: Column, start: int = 1) -> Column:
    """52 bits of the digest of a text as a BIGINT."""
    return F.conv(F.substring(F.md5(text.cast("binary")), start, DIGITS), 16, 10).cast("long")


def uniform(seed: int, purpose: str, *columns: Column | str) -> Column:
    """A draw from (0, 1)."""
    return (whole(_key(seed, purpose, *columns)) + 0.5) / RANGE


def order(seed: int, purpose: str, *columns: Column | str) -> Column:
    """A keyed digest to sort by."""
    return F.md5(_key(seed, purpose, *columns).cast("binary"))


def laplace(u: Column, scale: Column | float) -> Column:
    """Inverse distribution function of the centred Laplace law."""
    scale = scale if isinstance(scale, Column) else F.lit(float(scale))
    return -scale * F.signum(u - 0.5) * F.ln(1 - 2 * F.abs(u - 0.5))


def geometric(u: Column, v: Column, eps: Column | float, sensitivity: float = 1.0) -> Column:
    """Two-sided geometric law as the difference of two geometric draws: whole numbers only."""
    rate = (eps if isinstance(eps, Column) else F.lit(float(eps))) / sensitivity
    one = lambda x: F.floor(F.ln(x) / -rate)
    return (one(u) - one(v)).cast("long")


def pick_k(df: DataFrame, keys: list[str], count: str, seed: int, *columns: str, rank: str | None = None) -> DataFrame:
    """Without replacement `count` rows of every key, chosen by keyed order; their ranks stay in a column `rank`."""
    place = F.row_number().over(Window.partitionBy(*keys).orderBy(order(seed, "pick", *columns)))
    found = df.withColumn(rank or "_place", place).where(F.col(rank or "_place") <= F.col(count))
    return found if rank else found.drop("_place")
