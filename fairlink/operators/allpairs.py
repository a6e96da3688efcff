"""How many of all pairs of two parties' records are alike, without a blocking and without writing a pair.

Records of B that share values, and so bits, are put together. What a record of A has in common with the bits that all of them hold,
and the bits beyond, bound its similarity to each of them: only where the bound is above the threshold are single filters
compared, by a product of bit matrices, exact in 32-bit floats. Which records are put together decides the time, never the count.
"""

from __future__ import annotations

from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fairlink.functions import bits
from fairlink.operators.pairs import split
from fairlink.operators.tiles import _bits
from fairlink.settings import WORD_BITS, WORDS

MOST = 40_000  # records of a side of a cell, about
TOGETHER = 16  # records of B put together, at most
AT_ONCE = 128  # such sets compared at once


def _least(t: float) -> np.ndarray:
    """For every sum of ones the fewest common ones whose Dice is above the threshold."""
    every = np.arange(2 * WORDS * WORD_BITS + 1)
    both = np.arange(WORDS * WORD_BITS + 2)
    with np.errstate(divide="ignore", invalid="ignore"):
        above = np.where(every[:, None] > 0, 2.0 * both / every[:, None], 0.0) > t
    above[:, -1] = True  # no pair has so many
    return np.argmax(above, axis=1).astype(np.uint16)


def alike(a: np.ndarray, b: np.ndarray, t: float) -> int:
    """Pairs above the threshold; rows are words, ones, copies and, of b, the number of the set that the row is put into."""
    b = b[np.lexsort((b[:, WORDS], b[:, WORDS + 2]))]
    new = np.concatenate([[True], b[1:, WORDS + 2] != b[:-1, WORDS + 2]])
    first = np.maximum.accumulate(np.where(new, np.arange(len(b)), 0))
    starts = np.flatnonzero((np.arange(len(b)) - first) % TOGETHER == 0)
    ends = np.concatenate([starts[1:], [len(b)]])
    shared = _bits(np.bitwise_and.reduceat(b[:, :WORDS], starts, axis=0))
    # Common ones are at most those with the shared bits and the bits beyond: they are compared with what the largest record needs.
    bound = shared.sum(1) - (1 - t / 2) * np.maximum.reduceat(b[:, WORDS], starts) - 1e-2
    (*wa, na, ca), (*wb, nb, cb) = np.ascontiguousarray(a.T), np.ascontiguousarray(b[:, : WORDS + 2].T)
    xa = np.hstack([_bits(a[:, :WORDS]), na[:, None].astype(np.float32)])
    shared = np.hstack([shared, np.full((len(shared), 1), -t / 2, np.float32)])
    least, single, found = _least(t), bool((ca == 1).all() and (cb == 1).all()), 0
    for s in range(0, len(starts), AT_ONCE):
        near = shared[s : s + AT_ONCE] @ xa.T > bound[s : s + AT_ONCE, None].astype(np.float32)
        for own, low, high in zip(near, starts[s : s + AT_ONCE], ends[s : s + AT_ONCE], strict=True):
            at = np.flatnonzero(own)
            if not len(at):
                continue
            both = np.zeros((high - low, len(at)), dtype=np.uint16)
            for x, y in zip(wa, wb, strict=True):
                both += np.bitwise_count(y[low:high, None] & x[at])
            hit = both >= least[nb[low:high, None] + na[at]]
            found += int(np.count_nonzero(hit)) if single else int((cb[low:high, None] * ca[None, at])[hit].sum())
    return found


def matches(encoded: DataFrame, t: float, together: list[str]) -> DataFrame:
    """group_id, matched: the pairs of each group whose Dice is above the threshold, of records with the columns of encoded.

    Equal filters are compared once, with their numbers. A group's records are dealt to the cells of a square, in which each pair meets once.
    """
    kinds = encoded.groupBy("party", "group_id", *together, *bits.names(), "n_ones").agg(F.count("*").alias("copies"))
    sizes = encoded.groupBy("party", "group_id").agg(F.count("*").alias("n"))
    side = max(1, ceil((sizes.agg(F.max("n")).first()[0] or 0) / MOST))
    row = [*(F.col(w) for w in bits.names()), F.col("n_ones").cast("long"), F.col("copies")]
    every = F.explode(F.sequence(F.lit(0), F.lit(side - 1)))
    place = lambda *keys: F.pmod(F.xxhash64(*keys), F.lit(side)).cast("int")
    a, b = split(kinds)
    group = lambda: F.concat("group_id", F.lit("")).alias("group")  # noqa: E731  # both sides stem from the same rows
    left = a.select(group(), place(*bits.names()).alias("i"), every.alias("j"), F.array(*row).alias("_all"))
    right = b.select(group(), every.alias("i"), place(*together).alias("j"), F.array(*row, F.xxhash64(*together)).alias("_all"))
    width = pa.schema([("group_id", pa.string()), ("matched", pa.int64())])

    def compared(x: pa.Table, y: pa.Table) -> pa.Table:
        if not len(x) or not len(y):
            return width.empty_table()
        flat = lambda rows, n: rows["_all"].combine_chunks().flatten().to_numpy().reshape(-1, n)
        return pa.table([x["group"][:1], pa.array([alike(flat(x, WORDS + 2), flat(y, WORDS + 3), t)])], schema=width)

    keys = ["group", "i", "j"]
    cells = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(compared, "group_id string, matched long")
    return cells.groupBy("group_id").agg(F.sum("matched").alias("matched"))


def counts(encoded: DataFrame, own: DataFrame, t: float, together: list[str]) -> DataFrame:
    """tp, fp, tn, fn per group over all its pairs; own are the true pairs with their similarity."""
    side = lambda p: F.sum((F.col("party") == p).cast("long"))
    sizes = encoded.groupBy("group_id").agg((side("A") * side("B")).alias("every")).where("every > 0")
    true = own.groupBy("group_id").agg(F.count("*").alias("true"), F.sum((F.col("sim") > t).cast("long")).alias("found"))
    rows = sizes.join(matches(encoded, t, together), "group_id", "left").join(true, "group_id", "left").fillna(0, ["matched", "true", "found"])
    tp, matched, other = F.col("found"), F.col("matched"), F.col("every") - F.col("true")
    return rows.select("group_id", tp.alias("tp"), (matched - tp).alias("fp"), (other - matched + tp).alias("tn"), (F.col("true") - tp).alias("fn"))
