"""Accuracy, fairness and cost of a linkage."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fairlink.operators.block import BIN


def truth_pairs(a: DataFrame, b: DataFrame, key: str = "entity_id") -> DataFrame:
    """All true pairs of two parties: id_a, id_b, group_id (of A)."""
    left = a.select(key, F.col("rec_id").alias("id_a"), "group_id").distinct()
    right = b.select(key, F.col("rec_id").alias("id_b")).distinct()
    return left.join(right, key).select("id_a", "id_b", "group_id")


def number(pairs: DataFrame, condition: Column | None = None) -> Column:
    """How many pairs the rows stand for, by copies where there is such a column; with a condition those that meet it."""
    one = F.col("copies") if "copies" in pairs.columns else F.lit(1).cast("long")
    return F.sum(one if condition is None else F.when(condition, one).otherwise(0)).cast("long")


def confusion(pairs: DataFrame, truth: DataFrame | None = None) -> DataFrame:
    """tp, fp, tn, fn per group; with `truth`, pairs that no bin holds count as missed."""
    counts = pairs.groupBy("group_id").agg(
        number(pairs, F.col("pred") & F.col("truth")).alias("tp"),
        number(pairs, F.col("pred") & ~F.col("truth")).alias("fp"),
        number(pairs, ~F.col("pred") & ~F.col("truth")).alias("tn"),
        number(pairs, ~F.col("pred") & F.col("truth")).alias("fn"),
    )
    return counts if truth is None else with_truth(counts, truth)


def with_truth(counts: DataFrame, truth: DataFrame) -> DataFrame:
    """Counts whose missed pairs are all true ones that were not found."""
    every = truth.groupBy("group_id").agg(F.count("*").alias("all"))
    full = counts.join(every, "group_id", "full")
    zero = lambda c: F.coalesce(c, F.lit(0).cast("long"))
    return full.select("group_id", *(zero(c).alias(c) for c in ("tp", "fp", "tn")), (zero("all") - zero("tp")).alias("fn"))


def ratio(top: Column, bottom: Column) -> Column:
    return F.when(bottom == 0, F.lit(0.0)).otherwise(top / bottom)


def rates(counts: DataFrame) -> DataFrame:
    """False-positive and false-negative rate, precision, recall, F* and F1 per group."""
    tp, fp, tn, fn = (F.col(c) for c in ("tp", "fp", "tn", "fn"))
    keys = [c for c in counts.columns if c not in ("tp", "fp", "tn", "fn")]
    return counts.select(
        *keys, "tp", "fp", "tn", "fn",
        ratio(fp, fp + tn).alias("fpr"), ratio(fn, fn + tp).alias("fnr"), ratio(tp, tp + fp).alias("precision"),
        ratio(tp, tp + fn).alias("recall"), ratio(tp, tp + fp + fn).alias("fstar"), ratio(2 * tp, 2 * tp + fp + fn).alias("f1"),
    )


def overall(counts: DataFrame) -> DataFrame:
    return rates(counts.agg(*(F.sum(c).alias(c) for c in ("tp", "fp", "tn", "fn"))).withColumn("group_id", F.lit("all")))


def fairness(group_rates: DataFrame) -> DataFrame:
    """Equalised-odds loss, the larger of the gaps of both error rates, and fairness, 1 - loss."""
    gap = lambda c: F.max(c) - F.min(c)
    return group_rates.agg(gap("fpr").alias("fpr_gap"), gap("fnr").alias("fnr_gap")).withColumn("loss", F.greatest("fpr_gap", "fnr_gap")).withColumn("fairness", 1 - F.col("loss"))


def by_run(counts: DataFrame, keys: list[str]) -> DataFrame:
    """Per run: rates over all groups, the gaps of both error rates between groups, loss and fairness."""
    each = rates(counts.select(*keys, "group_id", "tp", "fp", "tn", "fn"))
    gap = lambda c: F.max(c) - F.min(c)
    sums = each.groupBy(*keys).agg(*(F.sum(c).alias(c) for c in ("tp", "fp", "tn", "fn")), gap("fpr").alias("fpr_gap"), gap("fnr").alias("fnr_gap"))
    tp, fp, tn, fn = (F.col(c) for c in ("tp", "fp", "tn", "fn"))
    loss = F.greatest("fpr_gap", "fnr_gap")
    return sums.select(
        *keys, ratio(fp, fp + tn).alias("fpr"), ratio(tp, tp + fn).alias("recall"), ratio(tp, tp + fp).alias("precision"), ratio(tp, tp + fp + fn).alias("fstar"),
        "fpr_gap", "fnr_gap", loss.alias("loss"), (1 - loss).alias("fairness"),
    )


def parity(counts: DataFrame) -> DataFrame:
    """Demographic parity and equal opportunity gaps."""
    total = F.col("tp") + F.col("fp") + F.col("tn") + F.col("fn")
    rows = counts.select(ratio(F.col("tp") + F.col("fp"), total).alias("rate"), ratio(F.col("tp"), F.col("tp") + F.col("fn")).alias("tpr"))
    return rows.agg((F.max("rate") - F.min("rate")).alias("parity_gap"), (F.max("tpr") - F.min("tpr")).alias("opportunity_gap"))


def cost(noisy_stats: DataFrame, runs: list[str] | None = None) -> DataFrame:
    """Per group the pairs that same-group comparison makes, real and fake, from bin sizes alone.

    noisy_stats: party, bin, group, n (originals), m (dummies); runs: further columns to keep apart.
    """
    runs = runs or []
    side = lambda p, c: F.coalesce(F.sum(F.when(F.col("party") == p, F.col(c))), F.lit(0))
    wide = noisy_stats.groupBy(*runs, *BIN, "group_id").agg(side("A", "n").alias("na"), side("B", "n").alias("nb"), side("A", "m").alias("ma"), side("B", "m").alias("mb"))
    plain, every = F.col("na") * F.col("nb"), (F.col("na") + F.col("ma")) * (F.col("nb") + F.col("mb"))
    out = wide.groupBy(*runs, "group_id").agg(F.sum(plain).cast("long").alias("real"), F.sum(every - plain).cast("long").alias("fake"))
    return out.withColumn("pairs", F.col("real") + F.col("fake")).withColumn("overhead", ratio(F.col("fake"), F.col("real")))


def communication(noisy_stats: DataFrame, words: int = 5) -> DataFrame:
    """Dummies sent and bytes of all filters per party and group."""
    return noisy_stats.groupBy("party", "group_id").agg(F.sum("m").cast("long").alias("dummies"), (F.sum(F.col("n") + F.col("m")) * words * 8).cast("long").alias("bytes"))


def histogram(pairs: DataFrame, buckets: int = 20) -> DataFrame:
    """Similarities of real pairs by group, class and bucket."""
    return pairs.where("NOT fake").groupBy("group_id", "truth", F.least(F.lit(buckets - 1), F.floor(F.col("sim") * buckets)).cast("int").alias("bucket")).agg(number(pairs).alias("n"))


def overlap_area(hist: DataFrame) -> DataFrame:
    """How much the score distributions of matches and others share, per group."""
    total = F.sum("n").over(Window.partitionBy("group_id", "truth"))
    share = hist.withColumn("p", F.col("n") / total)
    wide = share.groupBy("group_id", "bucket").agg(F.sum(F.when(F.col("truth"), F.col("p"))).alias("m"), F.sum(F.when(~F.col("truth"), F.col("p"))).alias("u"))
    return wide.groupBy("group_id").agg(F.sum(F.least(F.coalesce("m", F.lit(0.0)), F.coalesce("u", F.lit(0.0)))).alias("overlap"))


def exposure(sizes: DataFrame, size: str = "n", rare: int = 2) -> DataFrame:
    """Bins whose size no other bin of the party and table has, and bins of few records."""
    same = F.count("*").over(Window.partitionBy("party", "table_no", size))
    return sizes.withColumn("_same", same).groupBy("party", "group_id").agg(F.count_if(F.col("_same") == 1).alias("unique_bins"), F.count_if(F.col(size) < rare).alias("rare_bins"), F.count("*").alias("bins"))
