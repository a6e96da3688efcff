import pytest
from fairlink.functions import sqlfun
from fairlink.operators import block, encode
from fairlink.sources import people
from fairlink.sources.tables import table
from pyspark.sql import functions as F


@pytest.mark.parametrize("kind", ["csv", "json", "orc", "parquet"])
def test_round_trip_of_a_party(spark, small, tmp_path, kind):
    rows = people.parties(spark, small).select("party", "rec_id", "entity_id", "given", "surname", "age", "full_time")
    rows.write.format(kind).option("header", "true").mode("overwrite").save(f"{tmp_path}/{kind}")
    back = spark.read.format(kind).schema(rows.schema).option("header", "true").load(f"{tmp_path}/{kind}")
    assert back.exceptAll(rows).count() == 0 and back.count() == rows.count()


def test_bins_written_by_table_are_pruned(spark, small, tmp_path):
    rows = block.bit_labels(encode.encoded(people.parties(spark, small)))
    rows.write.partitionBy("table_no").parquet(f"{tmp_path}/bins")
    one = spark.read.parquet(f"{tmp_path}/bins").where("table_no = 3")
    assert "PartitionFilters: [isnotnull(table_no" in one._jdf.queryExecution().executedPlan().toString()
    assert one.count() == rows.where("table_no = 3").count()


def test_filters_and_columns_reach_the_scan(spark, small):
    plan = table(spark, small, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_quantity")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity" in plan and "l_extendedprice" not in plan


def test_sql_functions(spark):
    sqlfun.register(spark)
    row = spark.sql("SELECT fl_dice(15L, 51L) AS d, fl_dice(0L, 0L) AS z, round(fl_laplace(0.75D, 1D), 6) AS l").first()
    assert (row["d"], row["z"], row["l"]) == (0.5, 0.0, 0.693147)
    assert [r["token"] for r in spark.sql("SELECT token FROM fl_tokens('AbC', 2)").collect()] == ["ab", "bc"]


def test_lexicon_is_bounded_and_ranked(spark, small):
    rows = people.lexicon(spark, small, 50).collect()
    assert len(rows) == 50 and [r["place"] for r in rows] == list(range(50))
    assert [r["n"] for r in rows] == sorted((r["n"] for r in rows), reverse=True)


def test_groups_of_several_features(spark, small):
    rows = people.parties(spark, small, features=("gender", "age_band"))
    assert {r[0] for r in rows.select("group_id").distinct().collect()} == {"m/young", "m/old", "w/young", "w/old"}
    assert rows.groupBy("rec_id").count().agg(F.max("count")).first()[0] == 1
