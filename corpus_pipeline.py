"""From raw documents to packed training windows, in five stages.

Toxic documents go; of each class of near duplicates the document with the smallest doc_id stays;
passages that an earlier document holds are cut out; secrets are masked; what is left is packed.
Every stage takes all rows of the stage before. All but the last return the columns of documents;
texts that a stage leaves alone come out as they were.

Rows without doc_id pass the second and third stage unchanged. An empty table gives an empty
table of pieces.
"""

from __future__ import annotations

from fairlink.llm import near, packing, passages, secrets, toxicity
from fairlink.llm.common import documents, durable
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.without_toxic(docs.select(*COLUMNS), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    later = near.linked(docs).where("component_id <> doc_id").select("doc_id").distinct()
    return docs.select(*COLUMNS).join(later, "doc_id", "left_anti")


def cut_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    left = passages.without_repeats(docs, ("lang", "source"))
    # A cut may leave half a character at either side; such halves go too. Replacement characters that a text has of its
    # own stay: while halves are looked for, a pair of code points that stand for no character takes their place.
    own, sign = F.lit("\ufffd"), F.lit("\U0010fffe\U0010ffff")
    text = F.col("kept").cast("string")
    whole = F.replace(F.replace(F.make_valid_utf8(F.replace(text, own, sign)), own, F.lit("")), sign, own)
    text = F.when(F.col("n_removed") == 0, text).otherwise(whole)
    return left.withColumn("text", text).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secrets.masked(docs.select(*COLUMNS)).withColumn("n_chars", F.length("text").cast("long"))


def pack_windows(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    import public_tokenizers

    # Executors that have run the stages before have less memory left for the cache of words.
    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"), words=120_000)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("repeated_passages", cut_repeated_passages),
    ("secrets", mask_secrets),
    ("packing", pack_windows),
]

#: Learned scores and tokenizers are beyond SQL; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for _, stage in STAGES[:-1]:
        docs = durable(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
