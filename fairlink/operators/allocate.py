"""The tuners: flips for fairness, budgets for fairness or cost. All work on a few numbers per group."""

from __future__ import annotations

import math
from dataclasses import dataclass
from itertools import product

from fairlink.functions import theory


@dataclass(frozen=True)
class GroupStats:
    """What a tuner knows of a group; rates may be measured, sampled or public estimates."""

    group_id: str
    n_a: float
    n_b: float
    bins: float
    original_fp: float
    original_negatives: float
    fnr: float = 0.0


@dataclass(frozen=True)
class Knobs:
    eps: tuple[float, ...]
    flip: tuple[float, ...]
    loss: float
    cost: float
    at_border: bool = False


def _fpr(s: GroupStats, eps: float, flip: float, model, sensitivity: float) -> float:
    fake = theory.fake_pairs_collapsed(s.n_a, s.n_b, s.bins, eps, sensitivity)
    return theory.predicted_fpr(model(flip), fake, s.original_fp, s.original_negatives)


def loss_of(fprs: list[float], stats: list[GroupStats]) -> float:
    fnrs = [s.fnr for s in stats]
    return max(max(fprs) - min(fprs), max(fnrs) - min(fnrs))


def cost_of(stats: list[GroupStats], eps, sensitivity: float = 1.0) -> float:
    return sum(theory.fake_pairs_collapsed(s.n_a, s.n_b, s.bins, e, sensitivity) for s, e in zip(stats, eps, strict=True))


def flips(stats: list[GroupStats], eps: float, grid=None, model=theory.fp_prob_tabled, sensitivity: float = 1.0) -> Knobs:
    """Method A: equal budgets, flips that make the groups' predicted rates equal.

    Each group's rate is tabled over the grid. Up to three groups all combinations are tried; with more, a
    sweep over target levels takes each group's nearest flip. Many combinations tie where the dummies are clean;
    then flips nearest to one half are taken, as complements of like records are alike, then the smaller spread.
    """
    loss, chosen = _best_flips(stats, (eps,) * len(stats), grid, model, sensitivity)
    return Knobs((eps,) * len(stats), chosen, loss, cost_of(stats, (eps,) * len(stats), sensitivity))


def _best_flips(stats: list[GroupStats], eps: tuple[float, ...], grid, model, sensitivity: float) -> tuple[float, tuple[float, ...]]:
    grid = [i / 50 for i in range(51)] if grid is None else list(grid)
    table = [[_fpr(s, e, f, model, sensitivity) for f in grid] for s, e in zip(stats, eps, strict=True)]
    if len(stats) <= 3:
        combos = product(range(len(grid)), repeat=len(stats))
    else:
        levels = sorted({v for row in table for v in row})
        combos = (tuple(min(range(len(grid)), key=lambda i, r=row: (abs(r[i] - level), abs(grid[i] - 0.5))) for row in table) for level in levels)

    def rank(c):
        chosen = [grid[i] for i in c]
        return round(loss_of([row[i] for row, i in zip(table, c, strict=True)], stats), 9), round(sum(abs(f - 0.5) for f in chosen), 9), round(max(chosen) - min(chosen), 9), chosen

    loss, _, _, chosen = min(map(rank, combos))
    return loss, tuple(chosen)


def _bounds(overall: float, groups: int, eps_max: float | None) -> tuple[float, float]:
    """Total and least share of x = 1 / eps; no group goes without noise."""
    return 1 / overall, 1 / (eps_max or 10 * overall * groups)


def budgets(stats: list[GroupStats], overall: float, flip: float, objective: str = "fairness", eps_max: float | None = None, weight: float = 0.5, model=theory.fp_prob_tabled, sensitivity: float = 1.0) -> Knobs:
    """Method B: one flip, budgets under their harmonic sum that minimise fairness loss, cost, or both weighted."""
    total, least = _bounds(overall, len(stats), eps_max)
    rate = lambda s, x: _fpr(s, 1 / x, flip, model, sensitivity)
    base = cost_of(stats, [len(stats) * overall] * len(stats), sensitivity)

    def finish(xs: list[float]) -> Knobs:
        eps = tuple(1 / x for x in xs)
        border = any(x <= least * (1 + 1e-9) for x in xs)
        return Knobs(eps, (flip,) * len(stats), loss_of([rate(s, x) for s, x in zip(stats, xs, strict=True)], stats), cost_of(stats, eps, sensitivity), border)

    if objective == "cost":
        return finish(_cheapest(stats, total, least, sensitivity))
    if objective == "weighted":
        return _weighted(len(stats), total, least, finish, lambda k: k.loss + weight * k.cost / base)
    # Every group's rate is monotone in x: find the common level at which the shares sum to the total.
    falling = [rate(s, total) < rate(s, least) for s in stats]

    def share(s: GroupStats, level: float, down: bool) -> float:
        lo, hi = least, total
        for _ in range(80):
            mid = (lo + hi) / 2
            if (rate(s, mid) > level) == down:
                lo = mid
            else:
                hi = mid
        return (lo + hi) / 2

    if len(stats) == 2:
        lo, hi = least, total - least
        gap = lambda x: rate(stats[0], x) - rate(stats[1], total - x)
        if gap(lo) * gap(hi) > 0:
            x = min((lo, hi), key=lambda v: abs(gap(v)))
        else:
            up = gap(hi) > gap(lo)
            for _ in range(80):
                mid = (lo + hi) / 2
                if (gap(mid) < 0) == up:
                    lo = mid
                else:
                    hi = mid
            x = (lo + hi) / 2
        return finish([x, total - x])
    lo, hi = 0.0, max(max(rate(s, least), rate(s, total)) for s in stats)
    for _ in range(80):
        level = (lo + hi) / 2
        used = sum(share(s, level, d) for s, d in zip(stats, falling, strict=True))
        if (used > total) == all(falling):
            lo = level
        else:
            hi = level
    xs = [share(s, (lo + hi) / 2, d) for s, d in zip(stats, falling, strict=True)]
    scale = (total - least * len(xs)) / max(1e-12, sum(xs) - least * len(xs))
    return finish([least + (x - least) * scale for x in xs])


def _weighted(groups: int, total: float, least: float, finish, value, steps: int = 200) -> Knobs:
    """The best point of a grid over the shares; for more than two groups pairs of groups trade in turn until none gains."""
    xs = [total / groups] * groups
    best = finish(xs)
    for _ in range(50):
        before = value(best)
        for i in range(groups):
            for j in range(i + 1, groups):
                sum_ = xs[i] + xs[j]
                parts = [least + (sum_ - 2 * least) * n / steps for n in range(steps + 1)]
                tried = [[part if g == i else sum_ - part if g == j else x for g, x in enumerate(xs)] for part in parts]
                found = min(tried, key=lambda t: value(finish(t)))
                if value(finish(found)) < value(best) - 1e-15:
                    best, xs = finish(found), found
        if value(best) >= before - 1e-12:
            break
    return best


def _cheapest(stats: list[GroupStats], total: float, least: float, sensitivity: float) -> list[float]:
    """Minimum of sum(a x + c x^2) on the simplex: x = max(least, (nu - a) / 2c), nu by bisection."""
    a = [(s.n_a + s.n_b) * sensitivity / 2 for s in stats]
    c = [max(s.bins * sensitivity**2 / 4, 1e-9) for s in stats]
    at = lambda nu: [max(least, (nu - p) / (2 * q)) for p, q in zip(a, c, strict=True)]
    lo, hi = min(a), max(p + 2 * q * total for p, q in zip(a, c, strict=True))
    for _ in range(200):
        nu = (lo + hi) / 2
        if sum(at(nu)) > total:
            hi = nu
        else:
            lo = nu
    return at((lo + hi) / 2)


def both(stats: list[GroupStats], overall: float, flip: float, **options) -> Knobs:
    """Budgets first, then flips at those budgets."""
    first = budgets(stats, overall, flip, **options)
    loss, chosen = _best_flips(stats, first.eps, None, options.get("model", theory.fp_prob_tabled), options.get("sensitivity", 1.0))
    return Knobs(first.eps, chosen, loss, first.cost, first.at_border)


def harmonic(knobs: Knobs) -> float:
    return theory.overall_budget(list(knobs.eps))


def parallel(knobs: Knobs) -> float:
    return max(knobs.eps)


def sequential(knobs: Knobs, tables: int = 1) -> float:
    return math.fsum(knobs.eps) * tables
