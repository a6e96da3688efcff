"""Bit vectors as BIGINT columns w0, w1, ... of 60 bits, for code generation in the pair join."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from fairlink.settings import WORD_BITS, WORDS


def names(prefix: str = "w", words: int = WORDS) -> list[str]:
    return [f"{prefix}{i}" for i in range(words)]


def _sum(columns: list[Column]) -> Column:
    total = columns[0]
    for c in columns[1:]:
        total = total + c
    return total


def ones(prefix: str = "w", words: int = WORDS) -> Column:
    return _sum([F.bit_count(F.col(c)) for c in names(prefix, words)])


def common(a: str, b: str, words: int = WORDS) -> Column:
    return _sum([F.bit_count(F.col(x).bitwiseAND(F.col(y))) for x, y in zip(names(a, words), names(b, words), strict=True)])


def dice(both: Column, ones_a: Column, ones_b: Column) -> Column:
    """Twice the common ones by all ones; 0 where both are empty."""
    return F.when(ones_a + ones_b == 0, F.lit(0.0)).otherwise(2.0 * both / (ones_a + ones_b))


def jaccard(both: Column, ones_a: Column, ones_b: Column) -> Column:
    union = ones_a + ones_b - both
    return F.when(union == 0, F.lit(0.0)).otherwise(both / union)


def cosine(both: Column, ones_a: Column, ones_b: Column) -> Column:
    return F.when((ones_a == 0) | (ones_b == 0), F.lit(0.0)).otherwise(both / F.sqrt((ones_a * ones_b).cast("double")))


def overlap(both: Column, ones_a: Column, ones_b: Column) -> Column:
    return F.when((ones_a == 0) | (ones_b == 0), F.lit(0.0)).otherwise(both / F.least(ones_a, ones_b))


def hamming(both: Column, ones_a: Column, ones_b: Column) -> Column:
    return ones_a + ones_b - 2 * both


def word_of(positions: Column, word: int) -> Column:
    """The word with the bits of an array of positions that fall into it."""
    low = word * WORD_BITS
    own = F.filter(positions, lambda p: (p >= low) & (p < low + WORD_BITS))
    return F.aggregate(own, F.lit(0).cast("long"), lambda a, p: a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), (p - low).cast("int"))))


def bit(position: int, prefix: str = "w") -> Column:
    return F.shiftright(F.col(f"{prefix}{position // WORD_BITS}"), position % WORD_BITS).bitwiseAND(F.lit(1).cast("long"))
