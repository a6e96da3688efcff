"""The linear support vector classifier of all pairs of tiles.

At the least loss as many pairs of either class are on the wrong side of their margin, so that of the many pairs that are not
true only about as many count as there are true ones. The model is fitted on the true pairs and on others near the margin, and
a pass over all pairs adds those that it finds beyond the margin and not among them. A fit on some of the pairs is a lower bound of the
least loss and the loss of all pairs at its coefficients an upper one: passes end when both agree. Rows are kept in files, equal ones
as one with their number, and not in the driver, which holds a keyed part of bounded size for the start.

The objective and the penalty are those of Spark's learner, which stops at its most steps, or where a step along a corner no longer
helps, above the least loss; verdicts near the threshold differ by that.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fairlink.operators import tiles as T
from fairlink.sources.steps import written

PENALTY = 1e-3
SOFT = 1e-4  # width in which the hinge's corner is rounded at the end
LEVELS = (1.0, 1e-1, 1e-2, 1e-3, SOFT)
STEPS = 100  # at most, at each of them
TOLERANCE = 1e-6  # of the loss, as of Spark's own learner
START = 200_000  # rows of either class that the driver holds
NEAR = 8  # the first pass over others takes about so many of them for each true one
LEAST = 64  # sampled others that it takes at least
FLUSH = 1 << 16  # rows in a blob
KIND = "kind int, n long, rows binary"  # kind: 0 and 1 rows by class, 2 sums
WIDTH = pa.schema([("kind", pa.int32()), ("n", pa.int64()), ("rows", pa.binary())])


def _merged(parts: list[np.ndarray]) -> np.ndarray:
    """Equal rows as one; the last column is their number."""
    rows = np.concatenate(parts)
    own = np.ascontiguousarray(rows[:, :-1])
    _, first, place = np.unique(own.view(np.dtype((np.void, own.shape[1] * 8))).ravel(), return_index=True, return_inverse=True)
    return np.hstack([own[first], np.bincount(place, weights=rows[:, -1])[:, None]])


def _counted(x: np.ndarray, at: np.ndarray) -> np.ndarray:
    return np.vstack([x[:, at], np.ones(len(at))]).T


def _blob(kind: int, rows: np.ndarray) -> pa.RecordBatch:
    return pa.record_batch([pa.array([kind], pa.int32()), pa.array([len(rows)], pa.int64()), pa.array([rows.tobytes()], pa.binary())], schema=WIDTH)


def _read(made: DataFrame, labels: int, attributes: int, work: Callable, sums: int) -> DataFrame:
    """Rows that work(x, kept, truth, sums) -> [(kind, rows)] takes of the training half's pairs, and what it adds to sums."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, held, n = np.zeros(sums), {0: [], 1: []}, [0, 0]
        for batch in batches:
            for row in zip(*(batch.column(c) for c in ("table_no", "a", "b")), strict=True):
                for chunk in T.chunks(*(v.as_py() for v in row), labels, attributes, False):
                    for kind, rows in work(*chunk, total):
                        held[kind].append(rows)
                        n[kind] += len(rows)
                        if n[kind] >= FLUSH:
                            held[kind] = [_merged(held[kind])]
                            n[kind] = len(held[kind][0])
                            if n[kind] > FLUSH // 2:
                                yield _blob(kind, held[kind][0])
                                held[kind], n[kind] = [], 0
        for kind, parts in held.items():
            if parts:
                yield _blob(kind, _merged(parts))
        yield _blob(2, total)

    return written(made.mapInArrow(run, KIND), "margin")


def _sums(rows: DataFrame) -> np.ndarray:
    """In one order, whatever task ends first."""
    return reduce(np.add, [np.frombuffer(v) for v in sorted(r["rows"] for r in rows.where("kind = 2").select("rows").collect())])


def _first(k: int, share: float) -> Callable:
    """All true pairs, a keyed share of the others; numbers, sums and squares of the features by class."""

    def work(x, kept, truth, total):
        at, n = np.flatnonzero(kept & truth), x.shape[1]
        own, weight = x[:, at], kept.astype(float)
        both = np.concatenate([[weight.sum()], x @ weight, np.einsum("ij,ij,j->i", x, x, weight)])
        true = np.concatenate([[len(at)], own.sum(1), (own * own).sum(1)])
        total += np.concatenate([both - true, true])
        drawn = np.flatnonzero(np.random.default_rng([n, zlib.crc32(x[-1, :512].tobytes())]).random(n) < share)
        drawn = drawn[kept[drawn] & ~truth[drawn]]
        return [(y, _counted(x, i)) for y, i in ((0, drawn), (1, at)) if len(i)]

    return work


def _beyond(beta: np.ndarray, width: float, before: list[tuple[np.ndarray, float]]) -> Callable:
    """Other pairs nearer than a width to the margin that no pass before has taken; how many, and their loss."""

    def work(x, kept, truth, total):
        z = beta[0] + beta[1:] @ x
        at = np.flatnonzero(z > -1 - width)
        at = at[kept[at] & ~truth[at]]
        for own, wide in before:
            at = at[own[0] + own[1:] @ x[:, at] <= -1 - wide]
        if not len(at):
            return []
        total += [len(at), np.maximum(0.0, 1 + z[at]).sum()]
        return [(0, _counted(x, at))]

    return work


def _loss(x: np.ndarray, y: int, beta: np.ndarray, soft: float) -> np.ndarray:
    """Sums over rows of a class: the rounded loss, the hinge loss, and the gradient and curvature of the first."""
    one, weight = np.hstack([np.ones((len(x), 1)), x[:, :-1]]), x[:, -1]
    sign = 1.0 if y else -1.0
    over = 1 - sign * (one @ beta)
    tail = np.exp(-np.abs(over) / soft)
    share = weight * np.where(over > 0, 1.0, tail) / (1 + tail)
    hinge = np.maximum(0.0, over)
    curve = weight * tail / (1 + tail) ** 2 / soft
    return np.concatenate([[weight @ (hinge + soft * np.log1p(tail)), weight @ hinge], -sign * (one.T @ share), ((one.T * curve) @ one).ravel()])


def _least(evaluate: Callable, beta: np.ndarray, total: float, ridge: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, float]:
    """Coefficients of the least loss and their hinge loss, by damped Newton steps at ever sharper corners; those of size 0 stay 0.

    The curvature may vanish where no row is near its corner; damping is in proportion to the most that there can be.
    """
    d, used = len(beta), size > 0

    def at(beta, soft):
        s = evaluate(beta, soft)
        more = 0.5 * float(ridge @ (beta * beta))
        return s[0] / total + more, s[1] / total + more, s[2 : 2 + d] / total + ridge * beta, s[2 + d :].reshape(d, d) / total + np.diag(ridge)

    hinge = np.inf
    for soft in LEVELS:
        (loss, hinge, slope, curve), damp = at(beta, soft), 0.0
        for _ in range(STEPS):
            step = np.zeros(d)
            step[used] = np.linalg.solve((curve + np.diag((damp + 1e-12) * size / soft))[np.ix_(used, used)], slope[used])
            gain = float(slope @ step)
            if gain <= 0.1 * TOLERANCE * loss and (damp < 1e-8 or gain <= 1e-12 * loss):
                break
            found = at(beta - step, soft)
            if found[0] <= loss - 0.1 * gain:
                beta, (loss, hinge, slope, curve) = beta - step, found
                damp = 0.0 if damp < 1e-8 else damp / 16
            else:
                damp = max(1e-8, 16 * damp)
    return beta, hinge


def _decoded(batch: pa.RecordBatch, k: int) -> Iterator[tuple[int, np.ndarray]]:
    for kind, data in zip(batch.column("kind"), batch.column("rows"), strict=True):
        yield kind.as_py(), np.frombuffer(data.as_py()).reshape(-1, k + 1)


def _some(rows: DataFrame, k: int, share: float) -> np.ndarray:
    """A keyed share of rows in the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for kind, x in _decoded(batch, k):
                yield _blob(kind, x[np.random.default_rng([len(x), zlib.crc32(x[:512].tobytes())]).random(len(x)) < share])

    parts = sorted(r["rows"] for r in rows.mapInArrow(run, KIND).select("rows").collect())
    return np.frombuffer(b"".join(parts)).reshape(-1, k + 1)


def _evaluated(rows: DataFrame, k: int) -> Callable:
    """The sums of _loss over all rows, in the driver where they are few."""
    few = (rows.agg(F.sum(F.length("rows"))).first()[0] or 0) // (8 * (k + 1)) <= START
    local = [_some(rows.where(F.col("kind") == y), k, 1.0) for y in (0, 1)] if few else []

    def evaluate(beta, soft):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros(2 + (k + 1) * (k + 2))
            for batch in batches:
                for y, x in _decoded(batch, k):
                    total += _loss(x, y, beta, soft)
            yield _blob(2, total)

        return _loss(local[0], 0, beta, soft) + _loss(local[1], 1, beta, soft) if few else _sums(rows.mapInArrow(run, KIND))

    return evaluate


def fitted(made: DataFrame, labels: int, attributes: int, penalty: float = PENALTY, start: int = START) -> np.ndarray:
    """Coefficients, intercept first, of the least mean hinge loss with a penalty on coefficients of scaled features."""
    k = attributes + 1
    sizes = made.select(F.sum((F.length("a") * 1.0) * F.length("b"))).first()[0] or 0
    share = min(1.0, start / max(1.0, sizes / (8.0 * (T.MARKS + labels + T.WORDS)) ** 2))
    first = _read(made, labels, attributes, _first(k, share), 2 * (2 * k + 1))
    moments = _sums(first).reshape(2, -1)
    n, others, true = moments[:, 0].sum(), moments[0, 0], moments[1, 0]
    if not others or not true:  # one class only: it is what is predicted
        return np.concatenate([[1.0 if true else -1.0], np.zeros(k)])
    sums, squares = moments[:, 1 : k + 1].sum(0), moments[:, k + 1 :].sum(0)
    variance = np.maximum(0.0, squares - sums * sums / n) / (n - 1)
    ridge, size = np.concatenate([[0.0], penalty * variance]), np.concatenate([[1.0], np.where(variance > 1e-10, squares / n, 0.0)])

    part = min(1.0, start / true)
    x = [_some(first.where("kind = 0"), k, 1.0), _some(first.where("kind = 1"), k, part)]
    x = [rows * np.append(np.ones(k), of / max(1.0, rows[:, -1].sum())) for rows, of in zip(x, (others, true), strict=True)]
    local = lambda beta, soft: sum(_loss(x[y], y, beta, soft) for y in (0, 1))
    beta, _ = _least(local, np.concatenate([[-1.0], np.zeros(k)]), n, ridge, size)

    # A width that takes the wanted number of others, as the sampled ones tell.
    z = beta[0] + x[0][:, :-1] @ beta[1:]
    order = np.argsort(-z)
    wanted = max(LEAST, int(np.searchsorted(np.cumsum(x[0][order, -1]), NEAR * true)))
    width = max(0.1, -1 - float(z[order[min(len(z) - 1, wanted)]])) + 1e-6 if len(z) else 1.0
    taken, rows, lower = [], [first.where("kind = 1")], -np.inf
    while True:
        found = _read(made, labels, attributes, _beyond(beta, width, taken), 2)
        new, above = _sums(found)
        if taken and above / n <= TOLERANCE * (lower + above / n):
            return beta
        taken.append((beta, width))
        rows.append(found.where("kind = 0"))
        beta, lower = _least(_evaluated(reduce(DataFrame.unionByName, rows), k), beta, n, ridge, size)

