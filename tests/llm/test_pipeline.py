"""The pipeline on a small fixture against stages by brute force."""

import corpus_pipeline
from pyspark.sql import functions as F

from .conftest import odd_rows
from .test_operators import brute_classes


def fixture(spark, folder):
    docs = spark.createDataFrame([(*r[:5],) for r in odd_rows()] + [(900, "you idiot " * 3 + "moron scum", "en", "s", 1), (901, "keep token = \"9885103314b39ed955fd8ac9efa74c6fd87b66ee\" out", "en", "s", 1)], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(900, 1, 1), (901, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return docs


def test_stages(spark, tmp_path):
    folder = str(tmp_path)
    docs = fixture(spark, folder)
    left = corpus_pipeline.drop_toxic(spark, spark.read.parquet(f"{folder}/documents.parquet"), folder)
    assert left.columns == list(corpus_pipeline.COLUMNS) and left.count() == docs.count() - 1 and left.where("doc_id = 900").count() == 0
    single = corpus_pipeline.drop_near_duplicates(spark, left, folder)
    rows = [(r["doc_id"], r["text"] or "") for r in left.collect()]
    keep = [k for k, _, c in brute_classes(rows).elements() if k is None or k == c]
    assert sorted(r["doc_id"] if r["doc_id"] is not None else -1 for r in single.collect()) == sorted(-1 if k is None else k for k in keep)
    cut = corpus_pipeline.cut_repeated_passages(spark, single, folder)
    assert cut.columns == list(corpus_pipeline.COLUMNS) and cut.count() == single.count()
    same = cut.join(single.select("doc_id", F.coalesce("text", F.lit("")).alias("was")), "doc_id").where("text <> was")
    assert 0 < same.count() < 10
    masked = corpus_pipeline.mask_secrets(spark, cut, folder)
    assert masked.where("doc_id = 901").first()["text"] == 'keep token = "[SECRET]" out'
    pieces = corpus_pipeline.pack_windows(spark, masked, folder)
    assert pieces.select("doc_id").distinct().count() == masked.select("doc_id").distinct().count()


def test_run_is_the_stages(spark, tmp_path):
    fixture(spark, str(tmp_path))
    rows = corpus_pipeline.run(spark, str(tmp_path))
    assert rows.where("doc_id = 900").count() == 0 and rows.where("doc_id = 901").count() == 1
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "repeated_passages", "secrets", "packing"]


def test_empty_tables(spark, tmp_path):
    spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0



def test_cuts_keep_own_replacement_characters(spark, tmp_path):
    same = "this passage is long enough to be found again in the other text, é"
    rows = [(1, "start � " + same + "x"), (2, "other � head " + same + "� tail é"), (3, "é" * 20 + "ab" + "ü" * 30), (4, "à" * 3 + "é" * 19 + "ab" + "ü" * 29 + "è")]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = {r["doc_id"]: r["text"] for r in corpus_pipeline.cut_repeated_passages(spark, docs, str(tmp_path)).collect()}
    first: dict = {}
    for key, text in rows:
        data = text.encode()
        for i in range(len(data) - 49):
            first.setdefault(data[i : i + 50], key)
    for key, text in rows:
        data = text.encode()
        gone = {j for i in range(len(data) - 49) if first[data[i : i + 50]] < key for j in range(i, i + 50)}
        marked = data.replace("�".encode(), b"\x00\x00\x00")  # as many bytes, valid on their own
        left = bytes(b for j, b in enumerate(marked) if j not in gone).decode(errors="ignore").replace("\x00\x00\x00", "�")
        assert got[key] == left
