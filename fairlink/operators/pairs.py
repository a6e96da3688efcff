"""Candidate pairs of two parties' bins and their similarities."""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fairlink.functions import bits
from fairlink.operators.block import BIN
from fairlink.settings import DEFAULT, Linkage


def _side(rows: DataFrame, mark: str, tables: int) -> DataFrame:
    has = set(rows.columns)
    dummy = F.col("is_dummy") if "is_dummy" in has else F.lit(False)
    labels = [F.col(f"l{t}").alias(f"{mark}l{t}") for t in range(tables) if f"l{t}" in has]
    entity = F.col("entity_id") if "entity_id" in has else F.lit(None).cast("long")
    source = F.coalesce("parent_id", "rec_id") if "parent_id" in has else F.col("rec_id")
    extra = [F.col(c).alias(f"{mark}{c}") for c in rows.columns if c[0] == "t" and c[1:2].isdigit() or c == "tokens"]
    run = [F.col(c).alias(f"{c}_{mark}") for c in ("run", "copies", "half") if c in has]
    return rows.select(
        *BIN, F.col("group_id").alias(f"group_{mark}"), F.col("rec_id").alias(f"id_{mark}"), entity.alias(f"entity_{mark}"), dummy.alias(f"dummy_{mark}"), source.alias(f"source_{mark}"),
        *[F.col(f"w{i}").alias(f"{mark}{i}") for i in range(5)], F.col("n_ones").alias(f"ones_{mark}"), *labels, *extra, *run,
    )


def _compared(joined: DataFrame, *more: Column) -> DataFrame:
    """A joined row's marks and similarities; of each attribute where both sides carry its filter."""
    both = bits.common("a", "b")
    fake = F.col("dummy_a") | F.col("dummy_b")
    sims, j = [], 0
    while f"at{j}w0" in joined.columns:
        sims.append(bits.dice(bits.common(f"at{j}w", f"bt{j}w"), bits.ones(f"at{j}w"), bits.ones(f"bt{j}w")).alias(f"sim{j}"))
        j += 1
    if "atokens" in joined.columns:
        sims.append(token_dice(F.col("atokens"), F.col("btokens")).alias("plain"))
    if {"copies_a", "half_a"} <= set(joined.columns):  # of kinds: how many pairs the row stands for, and the half of A's records
        sims += [(F.col("copies_a") * F.col("copies_b")).alias("copies"), F.col("half_a").alias("half")]
    return joined.select(
        *more, "table_no", "label", "id_a", "id_b", F.col("group_a").alias("group_id"), fake.alias("fake"),
        (~fake & (F.col("entity_a") == F.col("entity_b"))).alias("truth"), both.alias("common"), "ones_a", "ones_b",
        bits.dice(both, F.col("ones_a"), F.col("ones_b")).alias("sim"), "source_a", *sims,
    )


def candidates(a: DataFrame, b: DataFrame, scope: str = "same_group", settings: Linkage = DEFAULT, first_table_only: bool = True, least: float | None = None, entities: bool = False) -> DataFrame:
    """Pairs of the same bin, once each: table_no, label, id_a, id_b, group_id, fake, truth, common, sim.

    An equi-join on table and label. A pair of originals counts in the first table whose labels agree,
    which the carried labels tell without a distinct; a dummy sits in one bin only. With `least`,
    pairs that cannot be more alike by their numbers of ones are left out before words are compared. With `entities` only
    true pairs are made.
    """
    left, right = _side(a, "a", settings.label_tables), _side(b, "b", settings.label_tables)
    joined = left.withColumn("_e", F.col("entity_a")).join(right.withColumn("_e", F.col("entity_b")), [*BIN, "_e"]) if entities else left.join(right, BIN)
    if scope == "same_group":
        joined = joined.where(F.col("group_a") == F.col("group_b"))
    fake = F.col("dummy_a") | F.col("dummy_b")
    if first_table_only and "al0" in left.columns:
        earlier = reduce(lambda x, y: x | y, [(F.col("table_no") > t) & (F.col(f"al{t}") == F.col(f"bl{t}")) for t in range(settings.label_tables)])
        joined = joined.where(fake | ~earlier)
    if least is not None:
        joined = joined.where(2.0 * F.least("ones_a", "ones_b") > least * (F.col("ones_a") + F.col("ones_b")))
    return _compared(joined)


def fakes(originals: DataFrame, dummies: DataFrame, settings: Linkage = DEFAULT) -> DataFrame:
    """Same-group pairs with a dummy, of many runs at once: dummies carry a column run, originals belong to all runs."""
    (oa, ob), (da, db) = split(originals), split(dummies)
    side = lambda rows, mark: _side(rows, mark, settings.label_tables)
    same = F.col("group_a") == F.col("group_b")
    made = [
        _compared(side(da, "a").join(side(ob, "b"), BIN).where(same), F.col("run_a").alias("run")),
        _compared(side(oa, "a").join(side(db, "b"), BIN).where(same), F.col("run_b").alias("run")),
        _compared(side(da, "a").join(side(db, "b"), BIN).where(same & (F.col("run_a") == F.col("run_b"))), F.col("run_a").alias("run")),
    ]
    return reduce(DataFrame.unionByName, made)


def near_candidates(a: DataFrame, b: DataFrame, strategy: DataFrame, settings: Linkage = DEFAULT, radius: int = 1) -> DataFrame:
    """Pairs of originals whose bins a strategy pairs (table_no, label_a, label_b), once each: in the first table where labels are so near."""
    left = _side(a, "a", settings.label_tables).withColumnRenamed("label", "label_a")
    right = _side(b, "b", settings.label_tables).withColumnRenamed("label", "label_b")
    joined = left.join(strategy, ["table_no", "label_a"]).join(right, ["table_no", "label_b"]).where(F.col("group_a") == F.col("group_b"))
    near = lambda t: F.bit_count(F.col(f"al{t}").bitwiseXOR(F.col(f"bl{t}"))) <= radius
    earlier = reduce(lambda x, y: x | y, [(F.col("table_no") > t) & near(t) for t in range(settings.label_tables)])
    return _compared(joined.where(~earlier).withColumn("label", F.col("label_a")))


def split(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    return rows.where("party = 'A'"), rows.where("party = 'B'")


def multi_party(parties: dict[str, DataFrame], **options) -> DataFrame:
    """Pairs of every two of any number of parties, with their names."""
    made = [candidates(parties[p], parties[q], **options).withColumn("parties", F.lit(f"{p}{q}")) for p, q in combinations(sorted(parties), 2)]
    return reduce(DataFrame.unionByName, made)


def bit_similarities() -> dict[str, Column]:
    """Other similarities of a pair row."""
    c, a, b = F.col("common"), F.col("ones_a"), F.col("ones_b")
    return {"jaccard": bits.jaccard(c, a, b), "cosine": bits.cosine(c, a, b), "overlap": bits.overlap(c, a, b), "hamming": bits.hamming(c, a, b)}


def token_dice(a: Column, b: Column) -> Column:
    """Dice of clear-text token sets: the ceiling that encoding is held against."""
    total = F.size(a) + F.size(b)
    return F.when(total == 0, F.lit(0.0)).otherwise(2.0 * F.size(F.array_intersect(a, b)) / total)


def edit_similarity(a: Column, b: Column) -> Column:
    longest = F.greatest(F.length(a), F.length(b))
    return F.when(longest == 0, F.lit(1.0)).otherwise(1 - F.levenshtein(a, b) / longest)
