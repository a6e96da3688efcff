import math

import pytest
from fairlink.functions import theory
from fairlink.operators import allocate
from hypothesis import given, settings
from hypothesis import strategies as st

#: flip, normal, exact, flip noise; threshold 0.8, 300 bits, fill 0.5
KNOWN = [(0.15, 1.0, 1.0, 0.9844), (0.18, 0.98267, 0.98375, None), (0.20, 0.5, 0.47699, 0.5), (0.22, 0.01319, 0.01209, None), (0.24, 0.0, 0.0, 0.0666), (0.28, 0.0, 0.0, 0.0019)]


@pytest.mark.parametrize(("flip", "normal", "exact", "noisy"), KNOWN)
def test_false_match_probability(flip, normal, exact, noisy):
    assert theory.fp_prob_normal(flip) == pytest.approx(normal, abs=2e-4)
    assert theory.fp_prob_exact(flip) == pytest.approx(exact, abs=2e-4)
    if noisy is not None:
        assert theory.fp_prob_flip_noise(flip) == pytest.approx(noisy, abs=2e-4)


def test_expected_dummies():
    assert theory.expected_dummies(0.1) == 5
    assert theory.expected_dummies(0.1, cap=20) == pytest.approx(4.323, abs=1e-3)
    for rounding, small, large in (("round", 4.998, 0.480), ("ceil", 5.254, 0.791), ("floor", 4.754, 0.291)):
        assert theory.expected_dummies(0.1, rounding=rounding) == pytest.approx(small, abs=1e-3)
        assert theory.expected_dummies(1.0, rounding=rounding) == pytest.approx(large, abs=1e-3)
    assert theory.expected_dummies(0.2, cap=3, rounding="round") == pytest.approx(1.126, abs=1e-3)


def test_critical_and_half_flip():
    assert [round(theory.critical_flip(t), 4) for t in (0.8, 0.7, 0.9)] == [0.3333, 0.4615, 0.1818]
    assert theory.half_flip() == pytest.approx(0.2)
    assert theory.fp_prob_exact(0.34) == 0
    assert theory.fp_prob_exact(1.0) == theory.fp_prob_normal(1.0) == 0
    assert theory.fp_prob_exact(0.0) == pytest.approx(1.0)


def test_predicted_rate_rises_with_budget_for_clean_dummies():
    at = [theory.predicted_fpr(0.0, theory.fake_pairs_collapsed(5000, 5000, 400, e), 50, 10_000) for e in (0.1, 1, 10)]
    assert at == sorted(at)


@settings(deadline=None)
@given(st.lists(st.floats(0.05, 20), min_size=1, max_size=5))
def test_budget_is_harmonic(eps):
    overall = theory.overall_budget(eps)
    assert 1 / overall == pytest.approx(sum(1 / e for e in eps))
    assert theory.overall_budget([theory.split_equal(overall, len(eps))] * len(eps)) == pytest.approx(overall)


def groups(na, nb=None, fp=(40, 20), negatives=(4000, 2000)):
    return [allocate.GroupStats(g, n, n, 400, f, q, 0.0) for g, n, f, q in zip("mw", na, fp, negatives, strict=False)]


@pytest.mark.parametrize("objective", ["fairness", "cost", "weighted"])
def test_method_b_keeps_the_budget(objective):
    found = allocate.budgets(groups((3000, 2500)), 1.0, 0.4, objective)
    assert allocate.harmonic(found) == pytest.approx(1.0, rel=1e-6)


def test_method_b_fairness_is_no_worse_than_equal_budgets():
    stats = groups((6000, 3000), fp=(90, 20))
    equal = allocate.loss_of([allocate._fpr(s, 2.0, 0.4, theory.fp_prob_normal, 1.0) for s in stats], stats)
    assert allocate.budgets(stats, 1.0, 0.4).loss <= equal + 1e-12


def test_method_b_cost_is_the_grid_optimum_and_guards_the_border():
    stats = groups((520, 500))
    found = allocate.budgets(stats, 1.0, 0.4, "cost")
    total, least = 1.0, 1 / 20
    grid = min(allocate.cost_of(stats, (1 / x, 1 / (total - x))) for x in [least + (total - 2 * least) * i / 5000 for i in range(5001)])
    assert found.cost == pytest.approx(grid, rel=1e-6)
    border = allocate.budgets(groups((6500, 3500)), 1.0, 0.4, "cost")
    assert border.at_border and math.isfinite(max(border.eps))


def test_method_b_moves_cost_from_the_large_group_to_the_small_one():
    stats = groups((3000, 2000))
    found = allocate.budgets(stats, 1.0, 0.4, "cost")
    assert found.eps[0] > 2.0 > found.eps[1]


def test_method_a_levels_the_groups():
    stats = groups((3000, 2000), fp=(100, 10))
    found = allocate.flips(stats, 2.0)
    equal = min(allocate.loss_of([allocate._fpr(s, 2.0, f, theory.fp_prob_normal, 1.0) for s in stats], stats) for f in (0.1, 0.2, 0.4, 0.8))
    assert found.loss <= equal + 1e-12
    assert set(found.eps) == {2.0}


def test_more_than_two_groups():
    stats = [allocate.GroupStats(str(i), 1000 * (i + 1), 900 * (i + 1), 300, 5 * (i + 1) ** 2, 1000 * (i + 1)) for i in range(4)]
    for objective in ("fairness", "cost"):
        found = allocate.budgets(stats, 0.5, 0.4, objective)
        assert allocate.harmonic(found) == pytest.approx(0.5, rel=1e-3)
    assert len(allocate.flips(stats, 2.0).flip) == 4
    assert allocate.both(stats[:2], 1.0, 0.4).loss >= 0


def test_tuners_of_many_groups():
    stats = [allocate.GroupStats(f"g{i}", 300 + 90 * i, 310 + 80 * i, 2000, 10 + 25 * i, 8000 + 900 * i, 0.01 * (i % 2)) for i in range(4)]
    for n in (2, 3, 4):
        some = stats[:n]
        both = allocate.both(some, 1.0, 0.1)
        first = allocate.budgets(some, 1.0, 0.1)
        fprs = [allocate._fpr(s, e, 0.1, theory.fp_prob_tabled, 1.0) for s, e in zip(some, first.eps, strict=True)]
        assert both.eps == first.eps and both.loss <= allocate.loss_of(fprs, some) + 1e-9
        heavy = allocate.budgets(some, 1.0, 0.4, "weighted", weight=100.0)
        assert abs(allocate.harmonic(heavy) - 1.0) < 1e-9
        assert heavy.cost <= allocate.budgets(some, 1.0, 0.4, "cost").cost * 1.001
    tied = [allocate.GroupStats("a", 500, 500, 900, 9, 9000, 0.3), allocate.GroupStats("b", 400, 400, 900, 9, 9000, 0.0)]
    assert allocate.both(tied, 1.0, 0.4).flip == allocate.flips(tied, 2.0).flip == (0.5, 0.5)


def test_tabled_law_is_the_normal_one():
    for i in range(51):
        assert abs(theory.fp_prob_tabled(i / 50) - theory.fp_prob_normal(i / 50)) < 2e-7
