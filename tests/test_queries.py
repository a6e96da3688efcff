"""Registered queries against their SQL on the smallest tables."""

import datetime
import math

import duckdb
import pytest
from fairlink.plans import catalogue, grids, methods, registry  # noqa: F401

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


def plain(v):
    if v is None or isinstance(v, (bool, str, datetime.date)):
        return str(v)
    if isinstance(v, float) and math.isnan(v):
        return "nan"
    if isinstance(v, list):
        return str([plain(x) for x in v])
    return f"{float(v):.6g}" if v else "0"


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_matches_sql(spark, small, duck, name):
    found = registry.QUERIES[name](spark, small)
    wanted = duck.execute(registry.ORACLES[name])
    names = [c[0] for c in wanted.description]
    assert sorted(names) == sorted(found.columns)
    order = sorted(names)
    left = sorted(tuple(plain(r[c]) for c in order) for r in found.collect())
    right = sorted(tuple(plain(r[names.index(c)]) for c in order) for r in wanted.fetchall())
    assert left == right


@pytest.mark.parametrize("name", ["budget_overall", "dp_ratio", "dummy_dice_curve", "expected_dummies", "fn_erf", "fn_laplace", "fp_prob_exact", "fp_prob_flip_noise", "fp_prob_normal"])
def test_reads_a_table(spark, small, name):
    assert registry.QUERIES[name](spark, small).inputFiles()


def test_statistics_of_equal_balances(spark, tmp_path):
    rows = [(k, "x", b) for k, b in ((9, 1.0), (4, 1.0), (7, 5.0), (2, 5.0), (5, 3.0), (1, None))]
    for order in (rows, rows[::-1]):
        spark.createDataFrame(order, "c_custkey long, c_mktsegment string, c_acctbal double").coalesce(1).write.mode("overwrite").parquet(f"{tmp_path}/customer.parquet")
        found = catalogue.agg_statistics(spark, str(tmp_path)).first()
        assert (found["poorest"], found["richest"]) == (4, 2)


def test_sessions_of_late_files(spark, tmp_path):
    """Sessions over several files out of order, kept in files and not in a table of the driver."""
    from fairlink.streaming import bins

    at = lambda day, hour: datetime.datetime(2024, 1, day, hour)
    for rows in ([(1, at(20, 0)), (1, at(20, 7)), (2, at(20, 1))], [(1, at(2, 0)), (1, at(20, 3)), (None, at(3, 0))], [(2, at(20, 6))]):
        spark.createDataFrame(rows, "user_id long, ts timestamp").coalesce(1).write.mode("append").parquet(f"{tmp_path}/events.parquet")
    found = bins.sessions(spark, f"{tmp_path}/events.parquet", "6 hours")
    assert found.inputFiles()
    assert sorted((r["user_id"] or 0, r["n"]) for r in found.collect()) == [(0, 1), (1, 1), (1, 3), (2, 2)]


def test_stateful_stream(spark, tmp_path):
    from fairlink.streaming import bins

    spark.createDataFrame([("a",), ("a",), ("b",)], "event_type string").write.parquet(f"{tmp_path}/in")
    stream = bins.stateful_noisy(spark.readStream.schema("event_type string").parquet(f"{tmp_path}/in"), 1.0)
    stream.writeStream.outputMode("update").format("memory").queryName("noisy_state").option("checkpointLocation", f"{tmp_path}/state").trigger(availableNow=True).start().awaitTermination()
    assert {r["event_type"]: r["n"] for r in spark.table("noisy_state").collect()} == {"a": 2, "b": 1}
