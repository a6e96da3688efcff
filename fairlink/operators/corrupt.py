"""Keyed corruption of attributes: single edits, look-alikes, sound rules, replaced values."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fairlink.functions import rng

# Fixed tables of look-alike and sound-alike strings.
LOOKS = {"o": "0", "l": "1", "s": "5", "m": "rn", "g": "9"}
SOUNDS = {"ph": "f", "ck": "k", "th": "t", "wh": "w", "c": "k"}
LETTERS = "abcdefghijklmnopqrstuvwxyz"
OPS = ("insert", "delete", "substitute", "transpose", "look", "sound")


def _first(value: Column, table: dict[str, str]) -> Column:
    """The value with the first table entry that it holds replaced everywhere."""
    out = value
    for old, new in reversed(table.items()):
        out = F.when(F.instr(value, old) > 0, F.replace(value, F.lit(old), F.lit(new))).otherwise(out)
    return out


def edit(value: Column, op: Column, place: Column, letter: Column) -> Column:
    """One edit of a text: op is a name of OPS, place a position from 1."""
    head = F.substr(value, F.lit(1), place - 1)
    tail = F.substr(value, place + 1)
    here, following = F.substr(value, place, F.lit(1)), F.substr(value, place + 1, F.lit(1))
    done = (
        F.when(op == "insert", F.concat(head, letter, here, tail))
        .when(op == "delete", F.concat(head, tail))
        .when(op == "substitute", F.concat(head, letter, tail))
        .when(op == "transpose", F.concat(head, following, here, F.substr(value, place + 2)))
        .when(op == "look", _first(value, LOOKS))
        .otherwise(_first(value, SOUNDS))
    )
    return F.when(F.coalesce(value, F.lit("")) == "", value).otherwise(done)


def edits(df: DataFrame, columns: list[str], share: float, seed: int, key: str = "entity_id", ops: tuple[str, ...] = OPS) -> DataFrame:
    """One keyed edit in one keyed attribute for a keyed share of the rows."""
    hit = rng.uniform(seed, "edit", key) < share
    which = F.floor(rng.uniform(seed, "column", key) * len(columns)).cast("int")
    op = F.get(F.array(*map(F.lit, ops)), F.floor(rng.uniform(seed, "op", key) * len(ops)).cast("int"))
    letter = F.substr(F.lit(LETTERS), (F.floor(rng.uniform(seed, "letter", key) * len(LETTERS)) + 1).cast("int"), F.lit(1))
    for i, c in enumerate(columns):
        place = (F.floor(rng.uniform(seed, "place", key) * F.length(c)) + 1).cast("int")
        df = df.withColumn(c, F.when(hit & (which == i), edit(F.col(c), op, place, letter)).otherwise(F.col(c)))
    return df


def replace(df: DataFrame, columns: list[str], shares: dict[str, float], by: str, seed: int, key: str = "entity_id") -> DataFrame:
    """New values in all the columns together, for a share of rows that depends on the group."""
    share = F.lit(0.0)
    for group, value in shares.items():
        share = F.when(F.col(by) == group, F.lit(value)).otherwise(share)
    hit = rng.uniform(seed, "replace", key) < share
    fresh = lambda c: F.substring(F.translate(rng.order(seed, f"new-{c}", key), "0123456789", "ghijklmnop"), 1, 7)
    return df.withColumns({c: F.when(hit, fresh(c)).otherwise(F.col(c)) for c in columns})
