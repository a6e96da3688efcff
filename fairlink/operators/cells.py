"""Trees and forests on all pairs of tiles: a learner of binned features needs the number of pairs of each cell of bins only.

A first pass counts the values of every feature, from which the cuts between bins are taken; a second one counts the pairs of every
cell. The cells are bounded by the bins, whatever the number of pairs. They are kept in slabs, one for each bin of the last
feature; a node of a tree is a box of cells, so that its histograms are sums along axes. Without a bootstrap the tree is that of
Spark's own learner on single pairs: a test holds it against that. A forest's tree draws a Poisson number for every pair,
which a cell of n pairs adds up to one Poisson number of mean n.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import ceil, prod, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fairlink.operators import tiles as T
from fairlink.settings import WORD_BITS, WORDS
from fairlink.sources.steps import written

K = WORDS * WORD_BITS + 1  # a similarity as one number: K times all ones and the common ones
BINS = 32
DEPTH = 5
TREES = 20
MOST = 1 << 26  # cells that a task may hold
CHUNK = 1 << 17  # pairs at once
FLUSH = 1 << 20  # pairs that are counted together: tiles may be small


def values() -> np.ndarray:
    """The similarity of every number that stands for one."""
    both, every = np.arange(2 * K * K) % K, np.arange(2 * K * K) // K
    return np.divide(2.0 * both, every, out=np.zeros(len(both)), where=every > 0)


def coded(table_no: int, a: bytes, b: bytes, labels: int, attributes: int, half: bool | None = None, places: list[np.ndarray] | None = None) -> Iterator[tuple]:
    """As tiles.chunks with numbers for similarities; with the places of numbers along each axis, each pair's cell in their stead."""
    ma, la, wa, fa = T._unpacked(a, labels, attributes)
    mb, lb, wb, fb = T._unpacked(b, labels, attributes)
    take = np.arange(len(ma)) if half is None else np.flatnonzero(ma[:, 2] == int(half))
    if not len(take):
        return
    looked = []
    for j, ((da, ia), (db, ib)) in enumerate(zip(fa, fb, strict=True)):
        xa, xb = T._bits(da), T._bits(db)
        code = (xa @ xb.T + K * (xa.sum(1)[:, None] + xb.sum(1)[None, :])).astype(np.int32)
        looked.append(((code if places is None else places[j][code])[:, ib], ia))
    xa, xb = T._bits(wa[take]), T._bits(wb)
    one = lambda x: np.ones((len(x), 1), np.float32)
    # Ones beside the bits: the product is the number itself, exact in 32-bit floats.
    xa, xb = np.hstack([xa, K * xa.sum(1, keepdims=True), one(xa)]), np.hstack([xb, one(xb), K * xb.sum(1, keepdims=True)])
    step = max(1, CHUNK // len(mb))
    for s in range(0, len(take), step):
        own = take[s : s + step]
        x = [table[place[own]] for table, place in looked]
        x.append((xa[s : s + step] @ xb.T).astype(np.int32))
        if places is not None:
            cell = places[attributes][x.pop()]
            for more in x:
                cell += more
            x = [cell]
        kept = np.ones(x[0].shape, dtype=bool)
        for t in range(table_no):
            kept &= la[own, t][:, None] != lb[:, t][None, :]
        truth = (ma[own, 0][:, None] == mb[:, 0][None, :]) & (ma[own, 1] == 1)[:, None] & (mb[:, 1] == 1)[None, :]
        yield [v.ravel() for v in x] if places is None else x[0].ravel(), kept.ravel(), truth.ravel()


def _tiles(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    for batch in batches:
        for row in zip(*(batch.column(c) for c in ("table_no", "a", "b")), strict=True):
            yield tuple(v.as_py() for v in row)


def _few(tiles: DataFrame) -> DataFrame:
    """Tiles in as many tasks as there are cores: each holds counts of its own."""
    return tiles.coalesce(max(1, tiles.sparkSession.sparkContext.defaultParallelism))


def value_counts(tiles: DataFrame, labels: int, attributes: int) -> list[np.ndarray]:
    """Of every feature how often each number occurs among the training half's pairs."""
    width = pa.schema([("feature", pa.int32()), ("number", pa.int32()), ("n", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, held, n = np.zeros((attributes + 1, 2 * K * K), dtype=np.int64), [], 0

        def flush() -> None:
            for j in range(attributes + 1):
                counts = np.bincount(np.concatenate([np.zeros(0, np.int32), *(x[j] for x in held)]))
                found[j, : len(counts)] += counts
            held.clear()

        for tile in _tiles(batches):
            for x, kept, _ in coded(*tile, labels, attributes, False):
                held.append(x if kept.all() else [v[kept] for v in x])
                n += len(held[-1][0])
                if n >= FLUSH:
                    flush()
                    n = 0
        flush()
        for j, counts in enumerate(found):
            at = np.flatnonzero(counts)
            yield pa.record_batch([pa.array(np.full(len(at), j, np.int32)), pa.array(at.astype(np.int32)), pa.array(counts[at])], schema=width)

    rows = _few(tiles).mapInArrow(run, "feature int, number int, n long").groupBy("feature", "number").agg(F.sum("n").alias("n")).toArrow()
    feature, number, n = (rows[c].to_numpy() for c in ("feature", "number", "n"))
    found = np.zeros((attributes + 1, 2 * K * K), dtype=np.int64)
    found[feature, number] = n
    return list(found)


def cuts(counts: np.ndarray, bins: int = BINS) -> np.ndarray:
    """Cuts half-way between neighbouring values: all of them where values are few, otherwise those nearest to equal shares of the pairs."""
    at = np.flatnonzero(counts)
    x, place = np.unique(values()[at], return_inverse=True)
    n = np.bincount(place, weights=counts[at])
    middle = (x[1:] + x[:-1]) / 2
    if len(x) <= bins:
        return middle
    out, upto, share = [], np.cumsum(n), n.sum() / bins
    target = share
    for i in range(1, len(x)):
        if abs(upto[i - 1] - target) < abs(upto[i] - target):
            out.append(middle[i - 1])
            target += share
    return np.array(out)


@dataclass(frozen=True)
class Grid:
    """The cuts of each feature; the last one is that of slabs."""

    cuts: tuple[np.ndarray, ...]

    @property
    def shape(self) -> tuple[int, ...]:
        """Of a slab's cells, the first feature the fastest: axes from last but one to first."""
        return tuple(len(c) + 1 for c in self.cuts[-2::-1])

    @property
    def slabs(self) -> int:
        return len(self.cuts[-1]) + 1

    @property
    def cells(self) -> int:
        return self.slabs * prod(self.shape)

    def places(self) -> list[np.ndarray]:
        out, size, x = [], 1, values()
        for c in self.cuts:
            out.append((np.searchsorted(c, x) * size).astype(np.int32))
            size *= len(c) + 1
        return out


def counted(tiles: DataFrame, labels: int, attributes: int, grid: Grid) -> DataFrame:
    """slab, other, true: how many pairs of the training half that are not true, and that are, each cell of the slab has."""
    width, size = pa.schema([("slab", pa.int32()), ("other", pa.binary()), ("true", pa.binary())]), prod(grid.shape)

    def emitted(every: np.ndarray, true: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        own = np.sort(np.concatenate([np.zeros(0, np.int32), *true]))
        for s in range(grid.slabs):
            low, high = np.searchsorted(own, [s * size, (s + 1) * size])
            t = np.bincount(own[low:high] - s * size, minlength=size)
            n = every[s * size : (s + 1) * size].astype(np.int64) - t
            if n.any() or t.any():
                yield pa.record_batch([pa.array([s], pa.int32()), pa.array([n.tobytes()], pa.binary()), pa.array([t.tobytes()], pa.binary())], schema=width)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        places, every, true, seen = grid.places(), np.zeros(grid.cells, dtype=np.uint32), [], 0
        one = np.uint32(1)
        for tile in _tiles(batches):
            for cell, kept, truth in coded(*tile, labels, attributes, False, places):
                if seen + len(cell) >= 1 << 32:  # a count might not fit
                    yield from emitted(every, true)
                    every[:], true, seen = 0, [], 0
                np.add.at(every, cell if kept.all() else cell[kept], one)
                true.append(cell[kept & truth])
                seen += len(cell)
        yield from emitted(every, true)

    def total(rows: pa.Table) -> pa.Table:
        add = lambda c: sum((np.frombuffer(v.as_py(), np.int64) for v in rows[c]), np.zeros(size, np.int64)).tobytes()
        return pa.table([rows["slab"][:1], pa.array([add("other")], pa.binary()), pa.array([add("true")], pa.binary())], schema=width)

    kind = "slab int, other binary, true binary"
    slabs = _few(tiles).mapInArrow(run, kind).repartition(grid.slabs, "slab").groupBy("slab").applyInArrow(total, kind)
    return written(slabs, "cells")


@dataclass
class Node:
    """A box of cells [low, high) along the features, and its pairs: other, true."""

    low: tuple[int, ...]
    high: tuple[int, ...]
    pairs: np.ndarray | None = None

    def within(self, slab: int) -> bool:
        return self.low[-1] <= slab < self.high[-1]

    def box(self) -> tuple[slice, ...]:
        return tuple(slice(x, y) for x, y in zip(self.low[-2::-1], self.high[-2::-1], strict=True))


def _histograms(slabs: DataFrame, grid: Grid, asked: list[tuple[int, Node, list[int]]], seed: int | None) -> list[list[np.ndarray]]:
    """For every (tree, node, features) the node's pairs by class along each of the features."""
    width = [[len(grid.cuts[j]) + 1 for j in features] for *_, features in asked]
    starts = np.cumsum([0, *(2 * w for ws in width for w in ws)])
    last, axes = len(grid.cuts) - 1, len(grid.shape)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = np.zeros(starts[-1])
        for batch in batches:
            for row in zip(*(batch.column(c) for c in ("slab", "other", "true")), strict=True):
                slab, *data = (v.as_py() for v in row)
                drawn, weights = None, None
                for i, (tree, node, features) in enumerate(asked):
                    if not node.within(slab):
                        continue
                    if drawn != tree:
                        drawn, weights = tree, [_drawn(np.frombuffer(d, np.int64), seed, tree, slab, c).reshape(grid.shape) for c, d in enumerate(data)]
                    first = sum(len(ws) for ws in width[:i])
                    for f, j in enumerate(features):
                        cells = out[starts[first + f] : starts[first + f + 1]].reshape(2, -1)
                        for c in range(2):
                            part = weights[c][node.box()]
                            if j == last:
                                cells[c, slab] += part.sum()
                            else:
                                axis = axes - 1 - j
                                cells[c, node.low[j] : node.high[j]] += part.sum(axis=tuple(x for x in range(axes) if x != axis))
        yield pa.record_batch([pa.array([out.tobytes()], pa.binary())], names=["sums"])

    total = np.zeros(starts[-1])
    for v in slabs.mapInArrow(run, "sums binary").toArrow()["sums"]:
        total += np.frombuffer(v.as_py())  # whole numbers: in any order the same
    flat = [total[x:y].reshape(2, -1) for x, y in zip(starts[:-1], starts[1:], strict=True)]
    out = []
    for ws in width:
        out.append(flat[: len(ws)])
        flat = flat[len(ws) :]
    return out


def _drawn(counts: np.ndarray, seed: int | None, *keys: int) -> np.ndarray:
    """With a seed as many pairs as a bootstrap takes of each cell: a pure function of the keys."""
    if seed is None:
        return counts
    out, at = np.zeros(len(counts), np.int64), np.flatnonzero(counts)
    out[at] = np.random.default_rng([seed, *keys]).poisson(counts[at])
    return out


def _impurity(pairs: np.ndarray) -> np.ndarray:
    n = np.maximum(1.0, pairs.sum(0))
    return 1.0 - (pairs[0] / n) ** 2 - (pairs[1] / n) ** 2


def _best(hist: np.ndarray, low: int, high: int):
    """(gain, bin that the right side begins with, left pairs, right pairs) of the best cut of a feature."""
    own = hist[:, low:high]
    left = np.cumsum(own, axis=1)[:, :-1]
    every = own.sum(1)
    right, n = every[:, None] - left, every.sum()
    if not left.shape[1] or not n:
        return 0.0, low, None, None
    gain = _impurity(every[:, None])[0] - left.sum(0) / n * _impurity(left) - right.sum(0) / n * _impurity(right)
    gain[(left.sum(0) < 1) | (right.sum(0) < 1)] = 0.0
    at = int(np.argmax(gain))
    return float(gain[at]), low + at + 1, left[:, at], right[:, at]


def grown(slabs: DataFrame, grid: Grid, trees: int = 1, depth: int = DEPTH, seed: int = 7) -> list[list[Node]]:
    """The leaves of each tree. One tree sees all pairs and features; of more, each sees a bootstrap and at each node the root of the features' number."""
    k, bootstrap = len(grid.cuts), seed if trees > 1 else None
    whole = tuple(len(c) + 1 for c in grid.cuts)
    open_nodes, leaves = [(t, Node((0,) * k, whole)) for t in range(trees)], [[] for _ in range(trees)]
    draw = np.random.default_rng([seed, trees])
    for _ in range(depth):
        if not open_nodes:
            break
        asked = [(t, n, sorted(draw.choice(k, ceil(sqrt(k)), replace=False).tolist()) if trees > 1 else list(range(k))) for t, n in open_nodes]
        found, open_nodes = _histograms(slabs, grid, asked, bootstrap), []
        for (t, node, features), hists in zip(asked, found, strict=True):
            node.pairs = hists[0].sum(1)
            tried = [(*_best(h, node.low[j], node.high[j]), j) for h, j in zip(hists, features, strict=True)]
            gain, at, left, right, j = max(tried, key=lambda x: x[0])
            if gain <= 0:
                leaves[t].append(node)
                continue
            put = lambda x, j=j, at=at: (*x[:j], at, *x[j + 1 :])
            for child in (Node(node.low, put(node.high), left), Node(put(node.low), node.high, right)):
                # A node of one class is split no more.
                (open_nodes if child.pairs.all() else leaves[t]).append((t, child) if child.pairs.all() else child)
    for t, node in open_nodes:
        leaves[t].append(node)
    return leaves


class Verdict:
    """Whether a cell's pairs are matches: the trees' shares of true pairs, added up, are above those of others."""

    def __init__(self, grid: Grid, leaves: list[list[Node]]):
        self.grid, self.leaves, self.table = grid, leaves, None

    def __getstate__(self):
        return {"grid": self.grid, "leaves": self.leaves, "table": None}

    def __call__(self, cell: np.ndarray) -> np.ndarray:
        if self.table is None:
            self.table = np.concatenate([self.slab(s).ravel() for s in range(self.grid.slabs)])
        return self.table[cell]

    def slab(self, s: int) -> np.ndarray:
        votes = np.zeros(self.grid.shape)
        for node in (n for tree in self.leaves for n in tree if n.within(s) and n.pairs.sum()):
            votes[node.box()] += (node.pairs[1] - node.pairs[0]) / node.pairs.sum()
        return votes > 1e-12


class Reader:
    """Reads a tile's pairs as cells of a grid."""

    def __init__(self, grid: Grid):
        self.grid, self.places = grid, None

    def __getstate__(self):
        return {"grid": self.grid, "places": None}

    def __call__(self, table_no: int, a: bytes, b: bytes, labels: int, attributes: int, half: bool | None = None) -> Iterator[tuple]:
        self.places = self.places or self.grid.places()
        return coded(table_no, a, b, labels, attributes, half, self.places)


def fitted(tiles: DataFrame, labels: int, attributes: int, trees: int = 1) -> tuple[Grid, list[list[Node]]] | None:
    """The grid and the leaves of a tree or forest; nothing where a task could not hold the cells."""
    grid = Grid(tuple(cuts(n) for n in value_counts(tiles, labels, attributes)))
    return (grid, grown(counted(tiles, labels, attributes, grid), grid, trees)) if grid.cells <= MOST else None


def scored(pairs: DataFrame, grid: Grid, leaves: list[list[Node]], features: list[str]) -> DataFrame:
    """Adds pred to single pairs."""
    votes = F.lit(0.0)
    for node in (n for tree in leaves for n in tree if n.pairs.sum()):
        inside = F.lit(True)
        for c, cut, low, high in zip(features, grid.cuts, node.low, node.high, strict=True):
            inside = inside & (F.col(c) > float(cut[low - 1]) if low else F.lit(True)) & (F.col(c) <= float(cut[high - 1]) if high <= len(cut) else F.lit(True))
        votes = votes + F.when(inside, float((node.pairs[1] - node.pairs[0]) / node.pairs.sum())).otherwise(0.0)
    return pairs.withColumn("pred", votes > 1e-12)
