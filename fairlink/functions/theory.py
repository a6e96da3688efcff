"""Closed forms of the method, as plain functions and as columns."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Fixed coefficients of the rational approximation of the error function.
ERF = (0.254829592, -0.284496736, 1.421413741, -1.453152027, 1.061405429)


def expected_dummies(eps: float, sensitivity: float = 1.0, cap: int | None = None, rounding: str | None = None) -> float:
    """Mean dummies of a bin and group: no deletions, optionally capped and rounded."""
    scale = sensitivity / eps
    q = math.exp(-1 / scale)
    if cap is None:
        return {None: scale / 2, "floor": 0.5 * q / (1 - q), "ceil": 0.5 / (1 - q), "round": 1 / (4 * math.sinh(1 / (2 * scale)))}[rounding]
    if rounding is None:
        return scale / 2 * (1 - math.exp(-cap / scale))
    shift = {"round": 0.5, "ceil": 1.0, "floor": 0.0}[rounding]
    return sum(0.5 * math.exp(-(k - shift) / scale) for k in range(1, cap + 1))


def dummy_dice(flip: float, ones: float, n_bits: int) -> float:
    """Expected similarity of a dummy and its source."""
    if flip >= 1:
        return 0.0
    return 1 / (1 + flip * n_bits / (2 * (1 - flip) * ones)) if ones else 0.0


def ones_cutoff(flip: float, threshold: float, n_bits: int) -> float:
    """Ones above which a dummy is taken for a match."""
    return math.inf if flip >= 1 else n_bits * threshold * flip / (2 * (1 - threshold) * (1 - flip))


def fp_prob_exact(flip: float, threshold: float = 0.8, n_bits: int = 300, fill: float = 0.5) -> float:
    """Tail of the binomial number of ones above the cutoff."""
    cut = ones_cutoff(flip, threshold, n_bits)
    if cut >= n_bits:
        return 0.0
    log = lambda k: math.lgamma(n_bits + 1) - math.lgamma(k + 1) - math.lgamma(n_bits - k + 1) + k * math.log(fill) + (n_bits - k) * math.log(1 - fill)
    return math.fsum(math.exp(log(k)) for k in range(math.floor(cut) + 1, n_bits + 1))


def fp_prob_normal(flip: float, threshold: float = 0.8, n_bits: int = 300, fill: float = 0.5) -> float:
    """The same tail by the normal law."""
    cut = ones_cutoff(flip, threshold, n_bits)
    if math.isinf(cut):
        return 0.0
    return 0.5 * (1 - math.erf((cut - n_bits * fill) / math.sqrt(2 * n_bits * fill * (1 - fill))))


def fp_prob_tabled(flip: float, threshold: float = 0.8, n_bits: int = 300, fill: float = 0.5) -> float:
    """The normal law by the approximation that the columns use, so that tuners and their SQL agree to the last digits."""
    cut = ones_cutoff(flip, threshold, n_bits)
    return 0.0 if math.isinf(cut) else 0.5 * (1 - erf_plain((cut - n_bits * fill) / math.sqrt(2 * n_bits * fill * (1 - fill))))


def erf_plain(x: float) -> float:
    a = ERF
    t = 1 / (1 + 0.3275911 * abs(x))
    poly = t * (a[0] + t * (a[1] + t * (a[2] + t * (a[3] + t * a[4]))))
    return math.copysign(1.0, x) * (1 - poly * math.exp(-x * x)) if x else 0.0


def fp_prob_flip_noise(flip: float, threshold: float = 0.8, n_bits: int = 300, fill: float = 0.5) -> float:
    """With the flips' own variance: closer to what is measured."""
    if flip <= 0:
        return 1.0
    t, p, f = threshold, fill, flip
    mean = 2 * (1 - t) * p * (1 - f) - t * f
    variance = 4 * (1 - t) ** 2 * p * (1 - f) + t * t * f - mean * mean
    return 0.5 * (1 + math.erf(math.sqrt(n_bits) * mean / math.sqrt(2 * variance)))


def critical_flip(threshold: float = 0.8) -> float:
    """The flip from which the exact tail is empty."""
    return 2 * (1 - threshold) / (2 - threshold)


def half_flip(threshold: float = 0.8, fill: float = 0.5) -> float:
    return 2 * (1 - threshold) * fill / (threshold + 2 * (1 - threshold) * fill)


def overall_budget(eps: list[float]) -> float:
    """Harmonic overall budget of group budgets."""
    return 1 / sum(1 / e for e in eps)


def split_equal(overall: float, groups: int) -> float:
    return overall * groups


def fake_pairs_collapsed(n_a: float, n_b: float, bins: float, eps: float, sensitivity: float = 1.0) -> float:
    """Expected fake pairs of a group from its totals."""
    return (n_a + n_b) * sensitivity / (2 * eps) + bins * sensitivity**2 / (4 * eps**2)


def predicted_fpr(p_fp: float, dummy_pairs: float, original_fp: float, original_negatives: float) -> float:
    """False-positive rate of a group with so many dummy pairs."""
    total = dummy_pairs + original_negatives
    return (p_fp * dummy_pairs + original_fp) / total if total else 0.0


# The same as columns.


def erf(x: Column) -> Column:
    """Rational approximation, absolute error 1.5e-7."""
    a = ERF
    t = 1 / (1 + 0.3275911 * F.abs(x))
    poly = t * (a[0] + t * (a[1] + t * (a[2] + t * (a[3] + t * a[4]))))
    return F.signum(x) * (1 - poly * F.exp(-x * x))


def capped_mean(n: Column, eps: Column, sensitivity: float = 1.0) -> Column:
    """Expected dummies under the cap n, before rounding."""
    scale = F.lit(sensitivity) / eps
    return scale / 2 * (1 - F.exp(-n / scale))


def curve(spark, steps: int = 51, threshold: float = 0.8, n_bits: int = 300, fill: float = 0.5, flips: DataFrame | None = None) -> DataFrame:
    """All three predictions of a dummy's false match over flips 0, 0.02, ..., or over those of a table."""
    if flips is None:
        flips = spark.range(steps).select((F.col("id") / (steps - 1)).alias("flip"))
    f = F.col("flip")
    cut = F.when(f < 1, n_bits * threshold * f / (2 * (1 - threshold) * F.nullif(1 - f, F.lit(0.0))))
    mean = 2 * (1 - threshold) * fill * (1 - f) - threshold * f
    variance = 4 * (1 - threshold) ** 2 * fill * (1 - f) + threshold**2 * f - mean * mean
    tail = binomial_tail(spark, n_bits, fill)
    joined = flips.withColumn("cut", cut).withColumn("k", F.when(F.col("cut") < n_bits, F.floor("cut") + 1))
    out = joined.join(F.broadcast(tail), "k", "left")  # n_bits + 1 rows
    return out.select(
        "flip",
        F.coalesce("tail", F.lit(0.0)).alias("exact"),
        F.when(F.col("cut").isNull(), 0.0).otherwise(0.5 * (1 - erf((F.col("cut") - n_bits * fill) / math.sqrt(2 * n_bits * fill * (1 - fill))))).alias("normal"),
        F.when(f == 0, 1.0).otherwise(F.coalesce(0.5 * (1 + erf(F.sqrt(F.lit(float(n_bits))) * mean / F.nullif(F.sqrt(2 * F.abs(variance)), F.lit(0.0)))), F.lit(0.0))).alias("flip_noise"),
    )


def binomial_tail(spark, n_bits: int, fill: float) -> DataFrame:
    """(k, tail): chance of k ones or more, by sums of logarithms over n_bits + 1 rows."""
    rows = spark.range(n_bits + 1).select(F.col("id").alias("k"))
    step = F.when(F.col("k") == 0, n_bits * math.log(1 - fill)).otherwise(F.ln((n_bits - F.col("k") + 1) / F.col("k")) + math.log(fill) - math.log(1 - fill))
    up = Window.orderBy("k").rowsBetween(Window.unboundedPreceding, 0)
    down = Window.orderBy(F.desc("k")).rowsBetween(Window.unboundedPreceding, 0)
    return rows.withColumn("log", F.sum(step).over(up)).withColumn("tail", F.sum(F.exp("log")).over(down)).select("k", "tail")
