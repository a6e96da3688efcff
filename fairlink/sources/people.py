"""Person records of two parties, derived from the given tables by keyed draws.

A person is a customer. Names and suburbs are words of a lexicon, common and rare ones by a square law;
gender and age stand for the protected features. Half of each party's records match.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fairlink.functions import rng
from fairlink.operators import corrupt
from fairlink.settings import LEXICON
from fairlink.sources.tables import table

MEN = ("AUTOMOBILE", "BUILDING", "MACHINERY")
SEED = 7


def lexicon(spark: SparkSession, sf_dir: str, size: int = LEXICON) -> DataFrame:
    """(word, n, place): the most frequent plain words of English texts, at most `size` of them."""
    words = table(spark, sf_dir, "documents").where("lang = 'en'").select(F.explode(F.split("text", "[ \n]")).alias("word"))
    counted = words.where(F.col("word").rlike("^[a-z]{3,10}$")).groupBy("word").agg(F.count("*").alias("n"))
    top = counted.orderBy(F.desc("n"), "word").limit(size)
    ranked = top.agg(F.sort_array(F.collect_list(F.struct((-F.col("n")).alias("minus"), "word"))).alias("ws"))
    return ranked.select(F.posexplode("ws").alias("place", "w")).select("w.word", (-F.col("w.minus")).alias("n"), F.col("place").cast("long").alias("place"))


def _word(words: Column, purpose: str, *keys: str) -> Column:
    u = rng.uniform(SEED, purpose, *keys)
    return F.get(words, F.floor(u * u * F.size(words)).cast("int"))


def persons(spark: SparkSession, sf_dir: str, copies: int = 1) -> DataFrame:
    """One row per customer with all attributes of the person view; with more copies, each customer stands for so many persons of other names."""
    # LEXICON words at most.
    words = lexicon(spark, sf_dir).agg(F.sort_array(F.collect_list(F.struct("place", "word"))).alias("s")).select(F.col("s.word").alias("words"))
    region, nation = table(spark, sf_dir, "region"), table(spark, sf_dir, "nation")
    places = nation.join(F.broadcast(region), nation.n_regionkey == region.r_regionkey).select("n_nationkey", "n_name", "r_name")
    orders = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.sort_array(F.collect_set("o_orderpriority")).alias("industries"), F.count("*").alias("orders"))
    base = (
        table(spark, sf_dir, "customer")
        .select("c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment")
        .join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
        .join(orders, F.col("c_custkey") == F.col("o_custkey"), "left")
        .join(F.broadcast(words))
    )
    if copies > 1:
        base = base.withColumn("_copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).withColumn("c_custkey", F.col("c_custkey").cast("long") + F.col("_copy") * 1_000_000_000_000)
    return base.select(
        F.col("c_custkey").cast("long").alias("entity_id"),
        _word(F.col("words"), "given", "c_custkey").alias("given"),
        _word(F.col("words"), "surname", "c_custkey").alias("surname"),
        _word(F.col("words"), "suburb", "c_nationkey").alias("suburb"),
        F.lpad((F.col("c_nationkey") * 100 + F.floor(rng.uniform(SEED, "postcode", "c_custkey") * 100)).cast("string"), 4, "0").alias("postcode"),
        F.when(F.col("c_mktsegment").isin(*MEN), "m").otherwise("w").alias("gender"),
        (18 + F.floor((F.col("c_acctbal") + 1000) / 11000 * 72)).cast("int").alias("age"),
        F.coalesce("industries", F.array().cast("array<string>")).alias("industries"),
        (F.coalesce("orders", F.lit(0)) >= 10).alias("full_time"),
        F.col("r_name").alias("area"),
        F.col("n_name").alias("mesh"),
        (rng.whole(F.concat(F.lit(f"{SEED}|party|"), F.col("c_custkey").cast("string"))) % 3).cast("int").alias("lot"),
    )


def with_groups(df: DataFrame, features: list[str]) -> DataFrame:
    """group_id: the product of protected features."""
    made = df.withColumn("age_band", F.when(F.col("age") <= 45, "young").otherwise("old"))
    return made.withColumn("group_id", F.concat_ws("/", *features)).drop("age_band")


def parties(spark: SparkSession, sf_dir: str, flavour: str = "clean", features: tuple[str, ...] = ("gender",), share: float = 1.0, copies: int = 1) -> DataFrame:
    """Records of both parties: party, rec_id, entity_id, attributes, group_id.

    Flavours: clean; dirty, where half of B's records have one edited attribute; biased, where name,
    suburb and postcode of B's records are replaced, more often for group w; census, as clean
    (its encoding uses the categorical attributes only). A share below 1 takes a keyed part of the persons: the smaller pair.
    """
    people = persons(spark, sf_dir, copies)
    if share < 1:
        people = people.where(rng.uniform(SEED, "share", "entity_id") < share)
    people = people.withColumn("age_band", F.when(F.col("age") <= 45, "young").otherwise("old")).withColumn("group_id", F.concat_ws("/", *features)).drop("age_band")
    a, b = people.where("lot <> 2").withColumn("party", F.lit("A")), people.where("lot <> 1").withColumn("party", F.lit("B"))
    if flavour == "dirty":
        b = corrupt.edits(b, ["given", "surname", "suburb", "postcode"], 0.5, SEED)
    elif flavour == "biased":
        b = corrupt.replace(b, ["surname", "suburb", "postcode"], {"w": 0.3, "m": 0.1}, "gender", SEED)
    return a.unionByName(b).drop("lot").withColumn("rec_id", F.concat_ws("-", "party", "entity_id"))


def three_parties(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Records of parties A, B and C; the keyed draw that makes two parties leaves every person with two of the three."""
    people = persons(spark, sf_dir).withColumn("group_id", F.col("gender"))
    made = [people.where(F.col("lot") != skip).withColumn("party", F.lit(p)) for p, skip in (("A", 2), ("B", 1), ("C", 0))]
    return reduce(DataFrame.unionByName, made).drop("lot").withColumn("rec_id", F.concat_ws("-", "party", "entity_id"))


def documents_as_records(spark: SparkSession, sf_dir: str, tokens: int = 16) -> DataFrame:
    """Whole texts as records: party by the parity of the source, truth by equal text, tokens by a sketch of all shingles.

    Tokens are the smallest digests of the text's runs of five words (of all its words, where it has fewer), so that a filter
    of fixed length holds long texts too and near copies share most of them.
    """
    docs = table(spark, sf_dir, "documents").where("text IS NOT NULL")
    number = F.regexp_extract("source", r"(\d+)$", 1).cast("int")
    words = F.split("text", "[ \n]+")
    runs = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("words") - 4)), lambda i: F.md5(F.array_join(F.slice(F.col("words"), i, 5), " ").cast("binary")))
    return docs.withColumn("words", words).select(
        F.when(number % 2 == 0, "A").otherwise("B").alias("party"),
        F.concat(F.lit("doc-"), F.col("doc_id").cast("string")).alias("rec_id"),
        F.col("doc_id").alias("entity_id"),
        F.md5(F.col("text").cast("binary")).alias("truth"),
        F.slice(F.array_sort(F.array_distinct(runs)), 1, tokens).alias("tokens"),
        F.when(F.col("lang") == "en", "en").otherwise("other").alias("group_id"),
    )


def parts_as_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts as categorical records of both parties."""
    parts = table(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("entity_id"), "p_brand", "p_type", "p_size", "p_name", F.lower(F.substring("p_type", 1, 1)).alias("group_id"))
    lot = (rng.whole(F.concat(F.lit(f"{SEED}|part|"), F.col("entity_id").cast("string"))) % 3).cast("int")
    return reduce(DataFrame.unionByName, [parts.where(lot != skip).withColumn("party", F.lit(p)) for p, skip in (("A", 2), ("B", 1))])
