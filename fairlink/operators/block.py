"""Blocking: bins by sampled filter bits, by attribute values, or one bin for all."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fairlink.functions import bits
from fairlink.settings import DEFAULT, Linkage

BIN = ["table_no", "label"]


def label(settings: Linkage, table_no: int, prefix: str = "w") -> Column:
    """The bits at a table's positions, put together."""
    total = F.lit(0).cast("long")
    for j, p in enumerate(settings.label_positions(table_no)):
        total = total + F.shiftleft(bits.bit(p, prefix), j)
    return total


def labels(encoded: DataFrame, settings: Linkage = DEFAULT) -> DataFrame:
    """Adds l0.., one label per table."""
    return encoded.withColumns({f"l{t}": label(settings, t) for t in range(settings.label_tables)})


def bit_labels(encoded: DataFrame, settings: Linkage = DEFAULT) -> DataFrame:
    """One row per record and table; the labels stay beside it for the first-table rule."""
    tables = F.array(*[F.struct(F.lit(t).alias("table_no"), F.col(f"l{t}").alias("label")) for t in range(settings.label_tables)])
    return labels(encoded, settings).withColumn("_b", F.explode(tables)).select("*", "_b.table_no", "_b.label").drop("_b")


def by_key(df: DataFrame, keys: list[str]) -> DataFrame:
    """Bins by values of attributes."""
    return df.withColumn("table_no", F.lit(0)).withColumn("label", F.concat_ws("|", *keys))


def none(df: DataFrame) -> DataFrame:
    return df.withColumn("table_no", F.lit(0)).withColumn("label", F.lit(0).cast("long"))


def near_labels(bins: DataFrame, label_bits: int) -> DataFrame:
    """Pairs of bins of one table whose labels differ in one bit at most, both existing."""
    flips = [F.lit(0).cast("long"), *(F.lit(1 << j).cast("long") for j in range(label_bits))]
    own = bins.select(*BIN).distinct()
    asked = own.withColumn("mask", F.explode(F.array(*flips))).select("table_no", F.col("label").alias("label_a"), F.col("label").bitwiseXOR(F.col("mask")).alias("label"))
    return asked.join(own, BIN).select("table_no", "label_a", F.col("label").alias("label_b"))


def bin_stats(blocked: DataFrame) -> DataFrame:
    """Rows of each party, bin and group: partial counts before one exchange."""
    return blocked.groupBy("party", *BIN, "group_id").agg(F.count("*").alias("n"))


def k_anonymous(blocked: DataFrame, k: int) -> DataFrame:
    """Bins of each table merged in label order until each holds k records: party, table, label, bin.

    The running sum is over bins of one party and table, not over records.
    """
    sizes = blocked.groupBy("party", *BIN).agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("party", "table_no").orderBy("label").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return sizes.select("party", *BIN, "n", F.floor(before / k).cast("long").alias("bin"))


def merged(blocked: DataFrame, k: int) -> DataFrame:
    """Bins of each table merged in label order until the parties hold k records together; the same bins for all parties."""
    sizes = blocked.groupBy(*BIN).agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("table_no").orderBy("label").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    into = sizes.select(*BIN, F.floor(before / k).cast("long").alias("_bin"))
    return blocked.join(into, BIN).withColumn("label", F.col("_bin")).drop("_bin")


def tiles(encoded: DataFrame, side: int = 8) -> DataFrame:
    """All pairs of two parties without one hot bin: a grid of side x side cells, in which each pair meets once."""
    own, cells = F.pmod(F.xxhash64("rec_id"), F.lit(side)), F.sequence(F.lit(0), F.lit(side - 1))
    label = F.when(F.col("party") == "A", own * side + F.col("_c")).otherwise(F.col("_c") * side + own)
    return encoded.withColumn("_c", F.explode(cells)).withColumn("table_no", F.lit(0)).withColumn("label", label.cast("long")).drop("_c")


def quality(stats: DataFrame, found_truth: DataFrame, all_truth: DataFrame, n_a: Column, n_b: Column) -> DataFrame:
    """Reduction ratio and pair completeness of a blocking."""
    return comparisons(stats).crossJoin(found_truth).crossJoin(all_truth).select(
        (1 - F.col("pairs") / (n_a * n_b)).alias("reduction"), (F.col("found") / F.col("truth")).alias("completeness")
    )


def comparisons(stats: DataFrame) -> DataFrame:
    """Pairs of records that meet in bins, counted from bin sizes without the join."""
    wide = stats.groupBy(*BIN).agg(F.sum(F.when(F.col("party") == "A", F.col("n"))).alias("a"), F.sum(F.when(F.col("party") == "B", F.col("n"))).alias("b"))
    return wide.agg(F.coalesce(F.sum(F.col("a") * F.col("b")), F.lit(0)).cast("long").alias("pairs"))


def hot_bins(blocked: DataFrame, settings: Linkage, most: int, extra_bits: int = 6) -> DataFrame:
    """Splits bins above `most` records by further label bits, the same for both parties.

    A split bin gains precision and may lose pairs that differ in the further bits, as any label
    does; bins below stay as they are. Only the hot bins' keys are joined back.
    """
    wide = [p for p in settings.label_positions(settings.label_tables)][:extra_bits]
    more = F.lit(0).cast("long")
    for j, p in enumerate(wide):
        more = more + F.shiftleft(bits.bit(p), settings.label_bits + j)
    hot = blocked.groupBy(*BIN).agg(F.count("*").alias("_n")).where(F.col("_n") > most).select(*BIN, F.lit(True).alias("_hot"))
    return blocked.join(hot, BIN, "left").withColumn("label", F.when(F.col("_hot"), F.col("label") + more).otherwise(F.col("label"))).drop("_hot")
