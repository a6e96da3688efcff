"""Differentially private bins: noisy dummy counts per group, dummy records, and their union."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fairlink.functions import bits, rng
from fairlink.operators.block import BIN, bin_stats
from fairlink.settings import DEFAULT, WORD_BITS, WORDS, Linkage
from fairlink.sources.steps import spread

KEYS = ["party", "table_no", "label", "group_id"]


def equal_knobs(spark, groups: list[str], settings: Linkage = DEFAULT) -> DataFrame:
    """The same budget and flip for every group; budgets add up harmonically to settings.eps."""
    return spark.createDataFrame([(g, settings.eps * len(groups), settings.flip) for g in groups], "group_id string, eps double, flip double")


def dummy_counts(stats: DataFrame, knobs: DataFrame, settings: Linkage = DEFAULT, rounding: str = "round", cap: bool = True, mechanism: str = "laplace") -> DataFrame:
    """Adds m, the dummies of each party, bin and group.

    mechanism: laplace or geometric; rounding: round, ceil or floor; with cap the count
    does not exceed the group's population in the bin. Knobs hold one row per group.
    """
    keyed = stats.join(F.broadcast(knobs), "group_id")
    u = rng.uniform(settings.seed, "noise", *KEYS)
    if mechanism == "geometric":
        drawn: Column = rng.geometric(u, rng.uniform(settings.seed, "noise2", *KEYS), F.col("eps"), settings.sensitivity)
    else:
        x = rng.laplace(u, F.lit(settings.sensitivity) / F.col("eps"))
        drawn = {"round": F.floor(x + 0.5), "ceil": F.ceil(x), "floor": F.floor(x)}[rounding]
    m = F.greatest(F.lit(0), drawn)
    return keyed.withColumn("m", (F.least(F.col("n"), m) if cap else m).cast("long"))


def record_dp_counts(blocked: DataFrame, eps: float, settings: Linkage = DEFAULT) -> DataFrame:
    """One draw per bin whatever the groups: the standard notion."""
    sizes = blocked.groupBy("party", *BIN).agg(F.count("*").alias("n"))
    x = rng.laplace(rng.uniform(settings.seed, "noise", "party", *BIN), settings.sensitivity / eps)
    return sizes.withColumn("m", F.least(F.col("n"), F.greatest(F.lit(0), F.floor(x + 0.5))).cast("long"))


def picked(blocked: DataFrame, counts: DataFrame, keys: list[str] = KEYS, settings: Linkage = DEFAULT) -> DataFrame:
    """The originals that dummies are made of: m of each key, without replacement."""
    some = counts.where("m > 0").select(*keys, "m")
    return rng.pick_k(blocked.join(some, keys), keys, "m", settings.seed, "rec_id", "table_no")


def flip_mask(word: int, flip: Column, seed: int, *keys: str) -> Column:
    """Each of the word's bits set with chance `flip`; two draws from every digest."""

    def pair(i: Column) -> Column:
        key = F.concat_ws("|", F.lit(f"{seed}|flip"), *[F.col(k).cast("string") for k in keys], F.lit(str(word)), i.cast("string"))
        bit = lambda start, at: F.when((rng.whole(key, start) + 0.5) / rng.RANGE < flip, F.call_function("shiftleft", F.lit(1).cast("long"), at)).otherwise(F.lit(0).cast("long"))
        return bit(1, (2 * i).cast("int")) + bit(rng.DIGITS + 1, (2 * i + 1).cast("int"))

    return F.aggregate(F.transform(F.sequence(F.lit(0), F.lit(WORD_BITS // 2 - 1)), pair), F.lit(0).cast("long"), lambda a, b: a + b)


def fast_mask(name: str, flip: Column, seed: int, *keys: str) -> Column:
    """As flip_mask, by 16 bits of a 64-bit hash a draw: flips to 1/65536."""

    def four(i: Column) -> Column:
        h = F.xxhash64(F.lit(f"{seed}|flip|{name}"), *keys, i)
        bit = lambda j: F.when(F.shiftrightunsigned(h, 16 * j).bitwiseAND(F.lit(65535)) < flip * 65536, F.call_function("shiftleft", F.lit(1).cast("long"), (4 * i + j).cast("int"))).otherwise(F.lit(0).cast("long"))
        return bit(0) + bit(1) + bit(2) + bit(3)

    return F.aggregate(F.transform(F.sequence(F.lit(0), F.lit(WORD_BITS // 4 - 1)), four), F.lit(0).cast("long"), lambda a, b: a + b)


def dummies(chosen: DataFrame, settings: Linkage = DEFAULT) -> DataFrame:
    """Dummy records: the chosen ones with flipped bits, in the same bin whatever the bits say.

    Needs a column flip. The parent stays with the owner. The chosen rows are few but take a digest for every two bits,
    so they are spread over all tasks.
    """
    chosen = spread(chosen, "rec_id", "table_no")
    masked = chosen.withColumns({f"w{i}": F.col(f"w{i}").bitwiseXOR(flip_mask(i, F.col("flip"), settings.seed, "rec_id", "table_no")) for i in range(WORDS)})
    own = [c for c in chosen.columns if c[0] == "t" and c[1:2].isdigit()]
    if own:  # the filters of attributes
        masked = masked.withColumns({c: F.col(c).bitwiseXOR(fast_mask(c, F.col("flip"), settings.seed, "rec_id", "table_no")) for c in own})
    made = masked.withColumn("n_ones", bits.ones().cast("int")).withColumn("parent_id", F.col("rec_id"))
    return made.withColumn("rec_id", F.concat(F.lit("d-"), F.substring(rng.order(settings.seed, "dummy", "rec_id", "table_no"), 1, 16))).withColumn("is_dummy", F.lit(True))


def inject(blocked: DataFrame, made: DataFrame, settings: Linkage = DEFAULT) -> DataFrame:
    """Originals and dummies together."""
    own = blocked.withColumn("is_dummy", F.lit(False)).withColumn("parent_id", F.lit(None).cast("string"))
    return own.unionByName(made.select(own.columns))


def opaque(rows: DataFrame, settings: Linkage = DEFAULT) -> DataFrame:
    """What the linkage unit gets: new ids, no parent, no mark, no entity."""
    return rows.withColumn("rec_id", rng.order(settings.seed, "opaque", "rec_id", "is_dummy")).drop("entity_id", "is_dummy", "parent_id")


def feature_dp(blocked: DataFrame, knobs: DataFrame, settings: Linkage = DEFAULT, **options) -> DataFrame:
    """Blocked records with each group's own noise in every bin."""
    counts = dummy_counts(bin_stats(blocked), knobs, settings, **options)
    chosen = picked(blocked, counts, KEYS, settings).join(F.broadcast(knobs.select("group_id", "flip")), "group_id")
    return inject(blocked, dummies(chosen, settings), settings)


def record_dp(blocked: DataFrame, eps: float, flip: float, settings: Linkage = DEFAULT) -> DataFrame:
    """Blocked records with noise that knows no groups."""
    counts = record_dp_counts(blocked, eps, settings)
    chosen = picked(blocked, counts, ["party", *BIN], settings).withColumn("flip", F.lit(flip))
    return inject(blocked, dummies(chosen, settings), settings)


def feature_runs(blocked: DataFrame, stats: DataFrame, knobs: DataFrame, settings: Linkage = DEFAULT) -> DataFrame:
    """Dummies of many runs in one pass: knobs hold (run, group_id, eps, flip). Originals are ranked once for all runs.

    A run's dummies are those that it has alone, for draws depend on keys and not on the other runs.
    """
    counts = dummy_counts(stats, knobs, settings).where("m > 0").select("run", *KEYS, "m", "flip")
    return dummies(_first(blocked, counts, KEYS, settings), settings)


def record_runs(blocked: DataFrame, knobs: DataFrame, settings: Linkage = DEFAULT) -> DataFrame:
    """The same with noise that knows no groups; knobs: (run, eps, flip)."""
    sizes = blocked.groupBy("party", *BIN).agg(F.count("*").alias("n")).crossJoin(F.broadcast(knobs))  # as many rows as runs
    x = rng.laplace(rng.uniform(settings.seed, "noise", "party", *BIN), F.lit(settings.sensitivity) / F.col("eps"))
    counts = sizes.withColumn("m", F.least(F.col("n"), F.greatest(F.lit(0), F.floor(x + 0.5))).cast("long")).where("m > 0")
    return dummies(_first(blocked, counts.select("run", "party", *BIN, "m", "flip"), ["party", *BIN], settings), settings)


def _first(blocked: DataFrame, counts: DataFrame, keys: list[str], settings: Linkage) -> DataFrame:
    most = counts.groupBy(*keys).agg(F.max("m").alias("_most"))
    ranked = rng.pick_k(blocked.join(most, keys), keys, "_most", settings.seed, "rec_id", "table_no", rank="_rank")
    return ranked.join(counts, keys).where(F.col("_rank") <= F.col("m")).drop("_most", "_rank")


def padded(blocked: DataFrame, k: int, flip: float, settings: Linkage = DEFAULT) -> DataFrame:
    """Every bin of a party filled up with dummies to k records; an original may serve several times."""
    sizes = blocked.groupBy("party", *BIN).agg(F.count("*").alias("_n")).where(F.col("_n") < k)
    rank = F.row_number().over(Window.partitionBy("party", *BIN).orderBy(rng.order(settings.seed, "pick", "rec_id", "table_no"))) - 1
    own = blocked.join(sizes, ["party", *BIN]).withColumn("_rank", rank)  # fewer than k rows a bin
    times = F.floor((k - F.col("_n") - F.col("_rank") + F.col("_n") - 1) / F.col("_n"))
    copies = own.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.greatest(times, F.lit(1))))).where(F.col("_copy") <= times)
    chosen = copies.withColumn("_own", F.col("rec_id")).withColumn("rec_id", F.concat_ws("#", "rec_id", F.col("_copy").cast("string"))).withColumn("flip", F.lit(flip))
    made = dummies(chosen, settings).withColumn("parent_id", F.col("_own")).drop("_n", "_rank", "_copy", "_own")
    return inject(blocked, made, settings)


def empirical_ratio(spark, size: int, eps: float, seeds: int | DataFrame, sensitivity: float = 1.0) -> DataFrame:
    """Noisy sizes of a bin and of its neighbour with one record less, over keyed draws: value, both counts, their ratio, the bound.

    The draws are so many, or one for each row of a table by its id. With two-sided whole-number noise and no clamp the ratio stays near exp(eps / sensitivity) at most.
    """
    draws = (seeds if isinstance(seeds, DataFrame) else spark.range(seeds)).select(F.explode(F.array(F.lit(size), F.lit(size - 1))).alias("size"), "id")
    value = F.col("size") + rng.geometric(rng.uniform(1, "ratio", "size", "id"), rng.uniform(2, "ratio", "size", "id"), eps, sensitivity)
    side = lambda n: F.count_if(F.col("size") == n)
    seen = draws.select("size", value.alias("value")).groupBy("value").agg(side(size).alias("own"), side(size - 1).alias("neighbour"))
    return seen.withColumn("ratio", F.col("own") / F.nullif(F.col("neighbour"), F.lit(0))).withColumn("bound", F.exp(F.lit(eps / sensitivity)))
