"""Document fingerprints from closed syncmers.

A window of K code points is an anchor when the smallest of its inner windows of S code points
lies at either end. That depends on the K code points alone, so an edit elsewhere in the text
never moves an anchor, unlike minimisers. The operator knows a text by all its anchors with their positions. The
likeness of two texts matches them by position: the n-th anchor of a hash in one with the n-th of it in the other, and of
these the longest chain that is in the same order in both; the likeness is the chain's share of all anchors of the two. So common
anchors that come in another order do not count. The fingerprint that is returned keeps SKETCH anchors, those
of the smallest distinct hashes where they first occur, in the order of the text: hash and position as hex.

Each text is compared with itself after an edit and with the next text in ascending doc_id (ties:
by text; null doc_ids first; after the last comes the first). Texts travel once, dealt by ranges
of doc_id; a range also gets the first text of the next one, of which there are as many as ranges.

Null texts count as empty. An empty text has an empty fingerprint, like only to another empty
one; a text shorter than K is one anchor.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fairlink.llm.common import RowBuffer, slices, text_or_empty

K, S, SKETCH = 16, 5, 64
RANGE_ROWS = 2000
MOST_RANGES = 40_000
FINGERPRINTS = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
_SCHEMA = pa.schema(
    [("doc_id", pa.int64()), ("n_chars", pa.int64()), *((n, pa.string()) for n in ("edited_sha256", "fingerprint", "edited_fingerprint")), ("near_edited", pa.float64()), ("near_next", pa.float64())]
)


def _mixed(x: np.ndarray) -> np.ndarray:
    """Uniform 32-bit values from 64-bit polynomial hashes."""
    x = x ^ (x >> np.uint64(31))
    x *= np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    return (x >> np.uint64(32)).astype(np.uint32)


def _least(h: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each run of width values, by doubling."""
    step, out = 1, h
    while 2 * step <= width:
        out = np.minimum(out[:-step], out[step:])
        step *= 2
    rest = width - step
    return np.minimum(out[: len(out) - rest], out[rest:]) if rest else out


def anchors(codes: np.ndarray, k: int = K, s: int = S) -> tuple[np.ndarray, np.ndarray]:
    """Starts of the closed syncmers of a row of code points, and the hashes of their windows."""
    n = len(codes)
    if n < k:
        return np.zeros(0, np.int64), np.zeros(0, np.uint32)
    inner = np.zeros(n - s + 1, np.uint32)
    for i in range(s):
        inner *= np.uint32(0x01000193)
        inner += codes[i : n - s + 1 + i]
    inner ^= inner >> np.uint32(15)
    inner *= np.uint32(0x85EBCA6B)
    inner ^= inner >> np.uint32(13)
    width = k - s + 1
    least = _least(inner, width)
    at = np.flatnonzero((inner[: len(least)] == least) | (inner[width - 1 :] == least))
    value = np.zeros(len(at), np.uint64)
    for i in range(k):
        value *= np.uint64(0x100000001B3)
        value += codes[at + i]
    return at, _mixed(value)


class Anchors:
    """The anchors of one text, and the order in which their numbered hashes are looked up."""

    def __init__(self, at: np.ndarray, hashes: np.ndarray):
        self.at, self.hashes = at, hashes
        self.order = np.argsort(hashes, kind="stable")
        ranked = hashes[self.order]
        new = np.flatnonzero(np.r_[True, ranked[1:] != ranked[:-1]]) if len(ranked) else np.zeros(0, np.int64)
        self.first = self.order[new]
        nth = np.arange(len(ranked)) - np.repeat(new, np.diff(np.r_[new, len(ranked)]))
        self.keys = (ranked.astype(np.uint64) << np.uint64(32)) | nth.astype(np.uint64)

    def fingerprint(self, size: int = SKETCH) -> str:
        kept = np.sort(self.first[:size])
        return np.stack([self.hashes[kept], self.at[kept]], 1).astype(">u4").tobytes().hex()


def anchored(texts: list[str]) -> list[Anchors]:
    """The anchors of each text; a text too short for one is one as a whole."""
    codes = np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32)
    at, hashes = anchors(codes)
    out = []
    starts = np.cumsum([0, *map(len, texts)])
    lo = np.searchsorted(at, starts[:-1])
    hi = np.maximum(lo, np.searchsorted(at, starts[1:] - (K - 1)))
    for i, text in enumerate(texts):
        if len(text) >= K or not text:
            out.append(Anchors(at[lo[i] : hi[i]] - starts[i], hashes[lo[i] : hi[i]]) if text else Anchors(at[:0], hashes[:0]))
            continue
        value = np.zeros(1, np.uint64)
        for c in codes[starts[i] : starts[i + 1]]:
            value *= np.uint64(0x100000001B3)
            value += np.uint64(c)
        out.append(Anchors(np.zeros(1, np.int64), _mixed(value + np.uint64(len(text)))))
    return out


def _chain(places: np.ndarray) -> int:
    """Length of the longest rising part of a row of distinct places."""
    if (places[1:] > places[:-1]).all():
        return len(places)
    tails: list[int] = []
    for x in places.tolist():
        k = bisect_left(tails, x)
        tails[k : k + 1] = [x]
    return len(tails)


def likeness(a: Anchors, b: Anchors) -> float:
    """Share of the anchors of two texts that match in order; 1.0 for two texts without any, 0.0 where one has none."""
    if not len(a.at) or not len(b.at):
        return float(len(a.at) == len(b.at))
    hit = np.minimum(np.searchsorted(b.keys, a.keys), len(b.keys) - 1)
    common = np.flatnonzero(b.keys[hit] == a.keys)
    mine, other = a.order[common], b.order[hit[common]]
    n = _chain(other[np.argsort(mine)])
    return n / (len(a.at) + len(b.at) - n)


def _ranges(docs: DataFrame) -> DataFrame:
    """doc_id, text, range (of doc_id), ahead: whether the row is a copy of the next range's first."""
    rows = docs.count()
    n = max(1, min(MOST_RANGES, rows // RANGE_ROWS))
    place = F.lit(0)
    if n > 1:
        cuts = docs.agg(F.percentile_approx("doc_id", [i / n for i in range(1, n)], 20 * n)).first()[0]
        cuts = sorted(set(cuts or []))
        # Two levels, so that a search compares with about two square roots of the cuts.
        side = max(1, int(len(cuts) ** 0.5))
        tops = [cuts[i] for i in range(0, len(cuts), side)]
        if cuts:
            below = F.array(*[F.array(*map(F.lit, cuts[i : i + side])) for i in range(0, len(cuts), side)])
            top = F.size(F.filter(F.array(*map(F.lit, tops)), lambda c: c <= F.col("doc_id")))
            place = F.when(F.col("doc_id").isNull() | (top == 0), 0).otherwise((top - 1) * side + F.size(F.filter(F.get(below, top - 1), lambda c: c <= F.col("doc_id"))))
    rows = docs.select("doc_id", text_or_empty().alias("text")).withColumn("range", place.cast("int"))
    firsts = [r for r in rows.groupBy("range").agg(F.min(F.struct(F.col("doc_id").isNotNull().alias("known"), "doc_id")).alias("first")).collect()]
    firsts.sort(key=lambda r: r["range"])
    heads = [(nxt["first"]["doc_id"], here["range"]) for here, nxt in zip(firsts, [*firsts[1:], *firsts[:1]], strict=True)]
    if not heads:
        return rows.withColumn("ahead", F.lit(False))
    # As many rows as ranges, MOST_RANGES at most.
    small = F.broadcast(docs.sparkSession.createDataFrame(heads, "head long, dealt int"))
    ahead = rows.join(small, F.col("doc_id").eqNullSafe(F.col("head"))).select("doc_id", "text", F.col("dealt").alias("range"), F.lit(True).alias("ahead"))
    return rows.withColumn("ahead", F.lit(False)).unionByName(ahead)


def fingerprint_rows(rows: Iterator[tuple]) -> Iterator[tuple]:
    """Result rows from (doc_id, text, range, ahead), sorted by range, ahead, doc_id, text."""

    def solve(part: list[tuple], following: tuple) -> Iterator[tuple]:
        texts = [r[1] for r in part]
        edited = [t[: len(t) - len(t) // 4] + u[: len(t) // 4] for t, u in zip(texts, [*texts[1:], following[1]], strict=True)]
        own, changed = anchored([*texts, following[1]]), anchored(edited)
        for i, (key, text, _, _) in enumerate(part):
            yield key, len(text), hashlib.sha256(edited[i].encode()).hexdigest(), own[i].fingerprint(), changed[i].fingerprint(), likeness(own[i], changed[i]), likeness(own[i], own[i + 1])

    part: list[tuple] = []
    size, closed = 0, None
    for row in rows:
        if row[2] == closed:  # further copies ahead of a range that is done
            continue
        if part and row[2] != part[-1][2]:
            raise ValueError("a range came without the row ahead")
        if part and (row[3] or size > 1_000_000):
            yield from solve(part, row)
            part, size = [], 0
        if row[3]:
            closed = row[2]
            continue
        part.append(row)
        size += len(row[1])


def fingerprints(docs: DataFrame) -> DataFrame:
    """Fingerprints of every text and its edit, and their likeness."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = RowBuffer(_SCHEMA)
        rows = (r for part in slices(batches, "doc_id", "text", "range", "ahead") for r in zip(*part, strict=True))
        for row in fingerprint_rows(rows):
            out.add(row)
            if out.full():
                yield out.take()
        yield out.take()

    dealt = _ranges(docs).repartition("range").sortWithinPartitions("range", "ahead", "doc_id", "text")
    return dealt.mapInArrow(run, FINGERPRINTS)
