"""All pairs of a bin as matrices: blocks of two parties' records of one bin and group, written once and read by every pass.

A pass holds one tile of some thousand records a side at a time and returns sums, so that no pair is ever written. Common ones
are a product of bit matrices, exact in 32-bit floats; an attribute's similarity is looked up among the tile's distinct
filters. Numbers are those of the pair join: a test holds them against it.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fairlink.operators.block import BIN
from fairlink.operators.pairs import split
from fairlink.settings import WORD_BITS, WORDS
from fairlink.sources.steps import written

SIDE = 2048  # records of a tile's side
CHUNK = 1 << 15  # pairs at once
KEYS = [*BIN, "group_id"]


MARKS = 3  # entity, whether it is known, whether the record is in the test half


def _packed(rows: pa.Table, columns: int, attributes: int) -> Iterator[bytes]:
    """Blocks of SIDE rows: sizes, marks, labels and words, then per attribute its distinct filters and each row's place among them."""
    whole = rows["_all"].combine_chunks().flatten().to_numpy().reshape(-1, columns)
    fixed = columns - attributes * WORDS
    for start in range(0, len(whole), SIDE):
        part = whole[start : start + SIDE]
        head, body = [len(part)], [part[:, :fixed].ravel()]
        for j in range(attributes):
            own = np.ascontiguousarray(part[:, fixed + j * WORDS : fixed + (j + 1) * WORDS])
            _, first, place = np.unique(own.view(np.dtype((np.void, WORDS * 8))).ravel(), return_index=True, return_inverse=True)
            head.append(len(first))
            body += [own[first].ravel(), place.ravel()]
        yield np.concatenate([np.array(head, dtype=np.int64), *body]).tobytes()


def _unpacked(data: bytes, labels: int, attributes: int):
    flat = np.frombuffer(data, dtype=np.int64)
    n, at, wide = int(flat[0]), 1 + attributes, MARKS + labels + WORDS
    fixed, at = flat[at : at + n * wide].reshape(n, wide), at + n * wide
    filters = []
    for u in flat[1 : 1 + attributes]:
        distinct, at = flat[at : at + u * WORDS].reshape(-1, WORDS), at + u * WORDS
        filters.append((distinct, flat[at : at + n]))
        at += n
    return fixed[:, :MARKS], fixed[:, MARKS : MARKS + labels], fixed[:, MARKS + labels :], filters


def _bits(words: np.ndarray) -> np.ndarray:
    eight = np.ascontiguousarray(words).astype("<i8").view(np.uint8).reshape(len(words), WORDS, 8)
    return np.unpackbits(eight, axis=2, bitorder="little")[:, :, :WORD_BITS].reshape(len(words), -1).astype(np.float32)


def _dice(a: np.ndarray, b: np.ndarray, ones_a: np.ndarray, ones_b: np.ndarray) -> np.ndarray:
    both, every = (a @ b.T).astype(np.float64), ones_a[:, None] + ones_b[None, :]
    return np.divide(2.0 * both, every, out=np.zeros_like(both), where=every > 0)


def written_tiles(blocked: DataFrame, half: Column, labels: int, attributes: int) -> DataFrame:
    """table_no, label, group_id, a, b: every bin's records of both parties in blocks, each of A beside each of B."""
    names = ["_entity", "_known", "_half", *(f"l{t}" for t in range(labels)), *(f"w{i}" for i in range(WORDS)), *(f"t{j}w{i}" for j in range(attributes) for i in range(WORDS))]
    schema = pa.schema([("table_no", pa.int32()), ("label", pa.int64()), ("group_id", pa.string()), ("a", pa.binary()), ("b", pa.binary())])

    def pack(a: pa.Table, b: pa.Table) -> pa.Table:
        out = []
        if len(a) and len(b):
            key = [a[c][0].as_py() for c in KEYS]
            left, right = [list(_packed(x, len(names), attributes)) for x in (a, b)]
            out = [(*key, x, y) for x in left for y in right]
        return pa.table([pa.array(c, f.type) for c, f in zip(zip(*out), schema, strict=True)] if out else [pa.array([], f.type) for f in schema], schema=schema)

    marks = [F.coalesce("entity_id", F.lit(0)).cast("long").alias("_entity"), F.col("entity_id").isNotNull().cast("long").alias("_known"), half.cast("long").alias("_half")]
    # One array a row: a group's columns cost more than its rows.
    rows = blocked.select(*KEYS, "party", F.array(*marks, *names[MARKS:]).alias("_all"))
    a, b = (x.drop("party").groupBy(*KEYS) for x in split(rows))
    return written(a.cogroup(b).applyInArrow(pack, "table_no int, label long, group_id string, a binary, b binary"), "tiles")


def chunks(table_no: int, a: bytes, b: bytes, labels: int, attributes: int, half: bool | None = None) -> Iterator[tuple]:
    """(features, kept, truth) of a tile's pairs: rows sim0.., sim; kept are pairs that no earlier table holds.

    With half only those of A's records that are (not) of the test half take part.
    """
    ma, la, wa, fa = _unpacked(a, labels, attributes)
    mb, lb, wb, fb = _unpacked(b, labels, attributes)
    take = np.arange(len(ma)) if half is None else np.flatnonzero(ma[:, 2] == int(half))
    if not len(take):
        return
    looked = []
    for (da, ia), (db, ib) in zip(fa, fb, strict=True):
        xa, xb = _bits(da), _bits(db)
        looked.append((_dice(xa, xb, xa.sum(1), xb.sum(1))[:, ib], ia))
    xa, xb = _bits(wa[take]), _bits(wb)
    na, nb = xa.sum(1), xb.sum(1)
    step = max(1, CHUNK // len(mb))
    for s in range(0, len(take), step):
        own = take[s : s + step]
        x = np.empty((attributes + 1, len(own), len(mb)))
        for j, (table, place) in enumerate(looked):
            x[j] = table[place[own]]
        x[attributes] = _dice(xa[s : s + step], xb, na[s : s + step], nb)
        kept = np.ones(x.shape[1:], dtype=bool)
        for t in range(table_no):
            kept &= la[own, t][:, None] != lb[:, t][None, :]
        truth = (ma[own, 0][:, None] == mb[:, 0][None, :]) & (ma[own, 1] == 1)[:, None] & (mb[:, 1] == 1)[None, :]
        yield x.reshape(attributes + 1, -1), kept.ravel(), truth.ravel()


class _Rows:
    """Sampled rows that add up by being put together."""

    def __init__(self, rows: np.ndarray):
        self.parts = [rows]

    def __add__(self, other: _Rows) -> _Rows:
        self.parts += other.parts
        return self

    def tolist(self) -> list[float]:
        return np.concatenate(self.parts).ravel().tolist()


def passed(tiles: DataFrame, labels: int, attributes: int, work: Callable, half: bool | None = None, reader: Callable = chunks) -> DataFrame:
    """group_id, truth, sums: what work(features, kept, truth) -> (truth, sums) pairs add up to over the tiles' pairs, per batch of them."""
    width = pa.schema([("group_id", pa.string()), ("truth", pa.bool_()), ("sums", pa.list_(pa.float64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict = {}
        for batch in batches:
            for row in zip(*(batch.column(c) for c in ("group_id", "table_no", "a", "b")), strict=True):
                group, table_no, a, b = (v.as_py() for v in row)
                for x, kept, truth in reader(table_no, a, b, labels, attributes, half):
                    for is_true, sums in work(x, kept, truth):
                        total[group, is_true] = total[group, is_true] + sums if (group, is_true) in total else sums
        keys = sorted(total)
        yield pa.record_batch([pa.array([k[0] for k in keys], pa.string()), pa.array([k[1] for k in keys], pa.bool_()), pa.array([total[k].tolist() for k in keys], pa.list_(pa.float64()))], schema=width)

    return tiles.mapInArrow(run, "group_id string, truth boolean, sums array<double>")


def collected(rows: DataFrame) -> dict:
    """The sums of a pass by (group_id, truth): as many as tasks, groups and classes reach the driver."""
    total: dict = {}
    for r in sorted(rows.collect(), key=lambda r: (r["group_id"], r["truth"], r["sums"])):  # in one order, whatever task ends first
        key, sums = (r["group_id"], r["truth"]), np.array(r["sums"])
        total[key] = total[key] + sums if key in total else sums
    return total


def judged(tiles: DataFrame, labels: int, attributes: int, verdict: Callable, half: bool | None = None, reader: Callable = chunks) -> DataFrame:
    """tp, fp, tn, fn per group: verdict(features) -> matches. Whole numbers, exact in doubles up to 2^53."""

    def work(x, kept, truth):
        match = verdict(x) & kept
        both, n, t = int((match & truth).sum()), int(kept.sum()), int((truth & kept).sum())
        m = int(match.sum())
        return [(True, np.array([both, t - both], dtype=float)), (False, np.array([m - both, n - t - m + both], dtype=float))]

    found = collected(passed(tiles, labels, attributes, work, half, reader))
    rows = [(g, *(int(found.get((g, t), (0, 0))[i]) for t, i in ((True, 0), (False, 0), (False, 1), (True, 1)))) for g in sorted({g for g, _ in found})]
    return tiles.sparkSession.createDataFrame(rows, "group_id string, tp long, fp long, tn long, fn long")


def _newton(fixed: np.ndarray, k: int) -> Callable:
    """Sums of the logistic loss at the coefficients (intercept first): number, squares and sums of features, loss, gradient, curvature."""

    def sums(x, weight, y):
        one = np.vstack([np.ones(x.shape[1]), x])
        z = fixed @ one
        p = 1 / (1 + np.exp(-z))
        loss = np.logaddexp(0, -z if y else z)
        r, h = (p - y) * weight, p * (1 - p) * weight
        return np.concatenate([one @ weight, (one * one) @ weight, [loss @ weight], one @ r, ((one * h) @ one.T).ravel()])

    def work(x, kept, truth):
        every, at = sums(x, kept.astype(float), 0), np.flatnonzero(truth & kept)
        if not len(at):
            return [(False, every)]
        own, unit = x[:, at], np.ones(len(at))
        return [(False, every - sums(own, unit, 0)), (True, sums(own, unit, 1))]

    return work


def _step(found: dict, beta: np.ndarray, balanced: bool, penalty: float):
    """Loss, and the Newton step, of the mean loss with a penalty on coefficients of scaled features."""
    d = len(beta)
    total, cells = sum(v[0] for v in found.values()), len(found)
    share = {c: total / cells / v[0] if balanced else 1.0 for c, v in found.items()}
    s = sum(share[c] * v for c, v in found.items())
    w, w2 = s[0], sum(share[c] ** 2 * v[0] for c, v in found.items())
    free = w - w2 / w
    variance = np.maximum(0.0, (s[d + 1 : 2 * d] - s[1:d] ** 2 / w) / free) if free > 0 else np.zeros(d - 1)
    used = np.concatenate([[True], variance > 1e-10])
    ridge = np.concatenate([[0.0], penalty * variance])
    gradient, curve = s[2 * d + 1 : 3 * d + 1] / w + ridge * beta, s[3 * d + 1 :].reshape(d, d) / w + np.diag(ridge)
    step = np.zeros(d)
    step[used] = np.linalg.lstsq(curve[np.ix_(used, used)], gradient[used], rcond=None)[0]
    return s[2 * d] / w + 0.5 * float(ridge @ (beta * beta)), step


def _descended(evaluate: Callable, beta: np.ndarray, balanced: bool, penalty: float, most: int = 60) -> np.ndarray:
    """Newton's method until a step is below 1e-6; a step that raises the loss is halved."""
    best, kept, step = np.inf, beta, np.zeros(len(beta))
    for _ in range(most):
        loss, found = _step(evaluate(beta), beta, balanced, penalty)
        if loss > best + 1e-12:
            step = step / 2
            beta = kept - step
            continue
        best, kept, step = loss, beta, found
        beta = kept - step
        if np.abs(step).max() < 1e-6:
            break
    return beta


def logistic(tiles: DataFrame, labels: int, attributes: int, balanced: bool, penalty: float = 1e-3, start: int = 200_000) -> np.ndarray:
    """Coefficients, intercept first, of the logistic model of all pairs of the training half.

    Newton's method over all pairs from a start that is found on a keyed part of them; the part decides how many passes it
    takes and not where it ends, for the loss has one minimum.
    """
    k = attributes + 1
    sizes = tiles.select(F.sum((F.length("a") * 1.0) * F.length("b"))).first()[0] or 0
    share = min(1.0, start / max(1.0, sizes / (8.0 * (MARKS + labels + WORDS)) ** 2))

    def some(x, kept, truth):
        draw = np.random.default_rng(x.shape[1] * 1_000_003 + int(kept.sum())).random(x.shape[1])
        out = []
        for y, of in ((False, kept & ~truth), (True, kept & truth)):
            at = np.flatnonzero(of & (draw < (share if not y else min(1.0, 2_000 * share))))
            if len(at):
                out.append((y, _Rows(x[:, at].T)))
        return out

    parts = passed(tiles, labels, attributes, some, half=False).collect()
    if {r["truth"] for r in parts} != {True, False}:
        counts = collected(passed(tiles, labels, attributes, _newton(np.zeros(k + 1), k), half=False))
        if len({t for _, t in counts}) < 2:  # one class only: it is what is predicted
            return np.concatenate([[np.inf if any(t for _, t in counts) else -np.inf], np.zeros(k)])
        first = np.zeros(k + 1)
    else:
        rows = [(r["group_id"], r["truth"], np.array(r["sums"]).reshape(-1, k).T) for r in parts]
        def local(beta):
            total: dict = {}
            for group, y, x in rows:
                n = 1.0 if balanced else 1 / (share if not y else min(1.0, 2_000 * share))
                (_, found), *_ = [v for v in _newton(beta, k)(x, np.ones(x.shape[1], bool), np.full(x.shape[1], y)) if v[0] == y]
                total[group, y] = total[group, y] + found * n if (group, y) in total else found * n
            return total
        first = _descended(local, np.zeros(k + 1), balanced, penalty)
    return _descended(lambda beta: collected(passed(tiles, labels, attributes, _newton(beta, k), half=False)), first, balanced, penalty)


def scored(pairs: DataFrame, beta: np.ndarray, features: list[str]) -> DataFrame:
    """Adds pred and score by the coefficients."""
    z = reduce(lambda x, y: x + y, [float(w) * F.col(c) for w, c in zip(beta[1:], features, strict=True)], F.lit(float(beta[0])))
    return pairs.withColumn("score", 1 / (1 + F.exp(-z))).withColumn("pred", z > 0)
