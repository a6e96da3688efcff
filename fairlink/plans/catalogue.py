"""Queries of the relational operators, functions and streams around the method."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fairlink.functions import rng, sqlfun, theory
from fairlink.operators import block, joins
from fairlink.plans.oracle import _erf, u
from fairlink.plans.registry import query, r6, rounded
from fairlink.sources import people
from fairlink.sources.tables import table
from fairlink.streaming import bins

# Sources and schema.


@query("SELECT c_custkey, c_nationkey, round(c_acctbal, 2) AS c_acctbal, c_mktsegment FROM customer")
def scan_customer(spark, sf_dir):
    return table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", F.round("c_acctbal", 2).alias("c_acctbal"), "c_mktsegment")


@query("SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45")
def scan_pruned_lineitem(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_quantity")


@query("SELECT event_id, (json_extract_string(props, '$.k'))::VARCHAR AS k FROM events")
def events_props_json(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "map<string,string>")["k"].alias("k"))


# Projections and filters.


@query("SELECT c_custkey, c_mktsegment || '-' || c_nationkey::VARCHAR AS tag, c_acctbal > 0 AS positive FROM customer")
def proj_person(spark, sf_dir):
    packed = table(spark, sf_dir, "customer").select("c_custkey", F.struct("c_mktsegment", "c_nationkey").alias("s"), "c_acctbal")
    return packed.select("c_custkey", F.concat_ws("-", "s.c_mktsegment", "s.c_nationkey").alias("tag"), (F.col("c_acctbal") > 0).alias("positive"))


@query("SELECT c_custkey FROM customer WHERE c_acctbal BETWEEN 0 AND 5000 AND NOT (c_nationkey IN (1, 2, 3)) AND c_mktsegment IS NOT DISTINCT FROM 'BUILDING'")
def filter_age_band(spark, sf_dir):
    c = table(spark, sf_dir, "customer")
    return c.where(F.col("c_acctbal").between(0, 5000) & ~F.col("c_nationkey").isin(1, 2, 3) & F.col("c_mktsegment").eqNullSafe("BUILDING")).select("c_custkey")


@query("SELECT p_partkey FROM part WHERE (p_type LIKE '%A%' OR regexp_matches(p_name, '[0-9]')) AND p_size IN (1, 5, 10, 20, 30)")
def filter_in_like(spark, sf_dir):
    return table(spark, sf_dir, "part").where("(p_type LIKE '%A%' OR p_name RLIKE '[0-9]') AND p_size IN (1, 5, 10, 20, 30)").select("p_partkey")


# Joins.

_LOT = "(('0x' || substr(md5('7|party|' || c_custkey::VARCHAR), 1, 13))::BIGINT % 3)"
_SIDES = f"a AS (SELECT c_custkey, c_nationkey, c_acctbal, c_mktsegment FROM customer WHERE {_LOT} <> 2), b AS (SELECT c_custkey, c_nationkey, c_acctbal, c_mktsegment FROM customer WHERE {_LOT} <> 1)"


def _sides(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    lot = rng.whole(F.concat(F.lit("7|party|"), F.col("c_custkey").cast("string"))) % 3
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment")
    return c.where(lot != 2), c.where(lot != 1)


@query(f"WITH {_SIDES} SELECT a.c_nationkey, a.c_mktsegment, count(*) AS pairs FROM a JOIN b ON a.c_nationkey = b.c_nationkey AND a.c_mktsegment = b.c_mktsegment GROUP BY ALL")
def join_bins(spark, sf_dir):
    a, b = _sides(spark, sf_dir)
    return joins.pair_counts(a, b, ["c_nationkey", "c_mktsegment"])


@query("SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def join_bcast_group(spark, sf_dir):
    return table(spark, sf_dir, "customer").join(F.broadcast(table(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


@query("SELECT a.s_suppkey AS sa, b.s_suppkey AS sb FROM supplier a, supplier b WHERE abs(a.s_acctbal - b.s_acctbal) < 10 AND a.s_suppkey <> b.s_suppkey")
def join_allpairs(spark, sf_dir):
    s = table(spark, sf_dir, "supplier")
    a, b = s.select(F.col("s_suppkey").alias("sa"), F.col("s_acctbal").alias("x")), s.select(F.col("s_suppkey").alias("sb"), F.col("s_acctbal").alias("y"))
    return a.join(b, (F.abs(F.col("x") - F.col("y")) < 10) & (F.col("sa") != F.col("sb"))).select("sa", "sb")


@query(f"WITH {_SIDES} SELECT a.c_custkey AS ka, b.c_custkey AS kb FROM a JOIN b ON abs(a.c_acctbal - b.c_acctbal) <= 5")
def join_band_acctbal(spark, sf_dir):
    a, b = _sides(spark, sf_dir)
    return joins.band(a.select(F.col("c_custkey").alias("ka"), F.col("c_acctbal").alias("x")), b.select(F.col("c_custkey").alias("kb"), F.col("c_acctbal").alias("y")), "x", "y", 5.0).select("ka", "kb")


@query("SELECT o_orderkey, e.event_id FROM orders ASOF JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events GROUP BY ALL) e ON o_custkey = e.user_id AND o_orderdate + INTERVAL 25 YEAR >= e.ts")
def join_asof_events(spark, sf_dir):
    # Orders end years before the events begin; they are moved on by 25 years, so that most have events before them and some after.
    orders = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("key"), (F.col("o_orderdate") + F.expr("INTERVAL 25 YEARS")).alias("at"), "o_orderkey")
    events = table(spark, sf_dir, "events").select(F.col("user_id").alias("key"), F.col("ts").alias("at"), "event_id").groupBy("key", "at").agg(F.max("event_id").alias("event_id"))
    return joins.as_of(orders, events, "key", "at", ["event_id"]).where("event_id IS NOT NULL").select("o_orderkey", "event_id")


@query("SELECT a.event_id AS first_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_interval_events(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    a, b = e.select("user_id", F.col("ts").alias("ta"), F.col("event_id").alias("first_id")), e.select("user_id", F.col("ts").alias("tb"), F.col("event_id").alias("next_id"))
    return joins.interval(a, b, "user_id", "ta", "tb", 3600).select("first_id", "next_id")


@query(f"WITH {_SIDES} SELECT c_custkey FROM a WHERE c_custkey IN (SELECT c_custkey FROM b)")
def join_semi_matched(spark, sf_dir):
    a, b = _sides(spark, sf_dir)
    return a.join(b, "c_custkey", "left_semi").select("c_custkey")


@query(f"WITH {_SIDES} SELECT c_custkey FROM a WHERE c_custkey NOT IN (SELECT c_custkey FROM b)")
def join_anti_missed(spark, sf_dir):
    a, b = _sides(spark, sf_dir)
    return a.join(b, "c_custkey", "left_anti").select("c_custkey")


@query(f"WITH {_SIDES} SELECT coalesce(a.c_custkey, b.c_custkey) AS k, a.c_custkey IS NOT NULL AS in_a, b.c_custkey IS NOT NULL AS in_b FROM a FULL JOIN b ON a.c_custkey = b.c_custkey")
def join_full_truth(spark, sf_dir):
    a, b = (x.select("c_custkey", F.lit(True).alias(n)) for x, n in zip(_sides(spark, sf_dir), ("in_a", "in_b"), strict=True))
    return a.join(b, "c_custkey", "full").select(F.col("c_custkey").alias("k"), F.coalesce("in_a", F.lit(False)).alias("in_a"), F.coalesce("in_b", F.lit(False)).alias("in_b"))


@query("SELECT a.doc_id AS a, b.doc_id AS b FROM documents a JOIN documents b ON md5(a.text) = md5(b.text) AND a.doc_id < b.doc_id")
def self_theta_docs(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("h"))
    return d.select("h", F.col("doc_id").alias("a")).join(d.select("h", F.col("doc_id").alias("b")), "h").where("a < b").select("a", "b")


@query("SELECT c_nationkey, o_orderpriority, count(*) AS n FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY ALL")
def join_salted(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey"), "o_orderkey", "o_orderpriority")
    return joins.salted(o, table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), "c_custkey", "o_orderkey", 8).groupBy("c_nationkey", "o_orderpriority").agg(F.count("*").alias("n"))


# Aggregation.


@query("SELECT c_nationkey, count(*) AS n, count(*) FILTER (WHERE c_acctbal < 0) AS negative, min(c_custkey) AS lo, max(c_custkey) AS hi FROM customer GROUP BY ALL")
def agg_bin_sizes(spark, sf_dir):
    return table(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.count("*").alias("n"), F.count_if(F.col("c_acctbal") < 0).alias("negative"), F.min("c_custkey").alias("lo"), F.max("c_custkey").alias("hi"))


@query("SELECT source, count(DISTINCT lang) AS langs, count(DISTINCT md5(text)) AS texts FROM documents GROUP BY ALL")
def agg_distinct_tokens(spark, sf_dir):
    return table(spark, sf_dir, "documents").groupBy("source").agg(F.countDistinct("lang").alias("langs"), F.countDistinct(F.md5(F.col("text").cast("binary"))).alias("texts"))


@query("SELECT label, bit_or(b) AS any_bits, bit_and(b) AS all_bits, bit_xor(b) AS odd_bits FROM (SELECT label, vec_id % 1024 AS b FROM embeddings) GROUP BY label")
def agg_bitor(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("label", (F.col("vec_id") % 1024).alias("b"))
    return e.groupBy("label").agg(F.bit_or("b").alias("any_bits"), F.bit_and("b").alias("all_bits"), F.bit_xor("b").alias("odd_bits"))


@query("SELECT c_mktsegment, round(stddev_samp(c_acctbal), 4) AS sd, round(corr(c_acctbal, c_custkey), 6) AS corr, arg_min(c_custkey, c_acctbal) AS poorest, arg_max(c_custkey, c_acctbal) AS richest, round(quantile_cont(c_acctbal, 0.5), 4) AS median FROM customer GROUP BY ALL")
def agg_statistics(spark, sf_dir):
    """Of customers with one balance the smallest key is taken, so that partitions and their order do not matter."""
    at = lambda key: F.when(F.col("c_acctbal").isNotNull(), F.struct("c_acctbal", key))
    return table(spark, sf_dir, "customer").groupBy("c_mktsegment").agg(
        F.round(F.stddev_samp("c_acctbal"), 4).alias("sd"), F.round(F.corr("c_acctbal", "c_custkey"), 6).alias("corr"), F.min_by("c_custkey", at(F.col("c_custkey"))).alias("poorest"),
        F.max_by("c_custkey", at((-F.col("c_custkey")).alias("minus"))).alias("richest"), F.round(F.percentile("c_acctbal", 0.5), 4).alias("median"),
    )


_CELLS = "SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY"


@query(f"{_CELLS} CUBE (c_nationkey, c_mktsegment)")
def cube_cost(spark, sf_dir):
    return table(spark, sf_dir, "customer").cube("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))


@query(f"{_CELLS} ROLLUP (c_nationkey, c_mktsegment)")
def rollup_cost(spark, sf_dir):
    return table(spark, sf_dir, "customer").rollup("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))


@query(f"{_CELLS} GROUPING SETS ((c_nationkey), (c_mktsegment), ())")
def gsets_group(spark, sf_dir):
    return table(spark, sf_dir, "customer").groupingSets([[F.col("c_nationkey")], [F.col("c_mktsegment")], []], "c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))


@query("SELECT quality, count(*) FILTER (WHERE toxic = 0) AS clean, count(*) FILTER (WHERE toxic = 1) AS toxic FROM labels GROUP BY ALL")
def pivot_confusion(spark, sf_dir):
    wide = table(spark, sf_dir, "labels").groupBy("quality").pivot("toxic", [0, 1]).count()
    return wide.select("quality", F.coalesce("0", F.lit(0)).alias("clean"), F.coalesce("1", F.lit(0)).alias("toxic"))


@query("UNPIVOT (SELECT doc_id, quality::BIGINT AS quality, toxic::BIGINT AS toxic FROM labels) ON quality, toxic INTO NAME kind VALUE mark")
def unpivot_labels(spark, sf_dir):
    return table(spark, sf_dir, "labels").select("doc_id", F.col("quality").cast("long"), F.col("toxic").cast("long")).unpivot("doc_id", ["quality", "toxic"], "kind", "mark")


@query()
def sketch_counts(spark, sf_dir):
    """Approximate distinct counts, quantiles and a mergeable sketch."""
    o = table(spark, sf_dir, "orders")
    part = o.groupBy("o_orderstatus").agg(F.hll_sketch_agg("o_custkey", 12).alias("s"), F.approx_count_distinct("o_custkey").alias("customers"), F.approx_percentile("o_totalprice", 0.5).alias("median"))
    return part.select("o_orderstatus", "customers", "median", F.hll_sketch_estimate("s").alias("sketched"))


# Windows, sorting, sets.


@query("SELECT c_custkey, c_nationkey FROM customer QUALIFY row_number() OVER (PARTITION BY c_nationkey ORDER BY md5('7|pick|' || c_custkey::VARCHAR)) <= 3")
def win_pick_dummies(spark, sf_dir):
    c = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey").withColumn("k", F.lit(3))
    return rng.pick_k(c, ["c_nationkey"], "k", 7, "c_custkey").select("c_custkey", "c_nationkey")


@query("SELECT o_custkey, o_orderkey, (rank() OVER w)::INTEGER AS r, (dense_rank() OVER w)::INTEGER AS d, (ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey))::INTEGER AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC)")
def win_best_match(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"))
    return table(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.ntile(4).over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")).alias("q"))


@query("SELECT c_nationkey, c_mktsegment, n, sum(n) OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment ROWS UNBOUNDED PRECEDING)::BIGINT AS running FROM (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY ALL)")
def win_running_bins(spark, sf_dir):
    sizes = table(spark, sf_dir, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))
    return sizes.withColumn("running", F.sum("n").over(Window.partitionBy("c_nationkey").orderBy("c_mktsegment").rowsBetween(Window.unboundedPreceding, 0)))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_events(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"))


@query("SELECT c_nationkey, c_mktsegment, n FROM (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY ALL) ORDER BY n DESC, c_nationkey, c_mktsegment LIMIT 10")
def topk_bins(spark, sf_dir):
    return table(spark, sf_dir, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "c_nationkey", "c_mktsegment").limit(10)


@query("SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def topk_per_record(spark, sf_dir):
    rank = F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    return table(spark, sf_dir, "orders").withColumn("r", rank).where("r <= 2").select("o_custkey", "o_orderkey")


@query("SELECT c_custkey AS k, 'customer' AS kind FROM customer UNION ALL SELECT s_suppkey, 'supplier' FROM supplier")
def set_union_dummies(spark, sf_dir):
    a = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("k"), F.lit("customer").alias("kind"))
    return a.unionByName(table(spark, sf_dir, "supplier").select(F.lit("supplier").alias("kind"), F.col("s_suppkey").alias("k")))


@query("SELECT o_custkey AS k FROM orders INTERSECT SELECT user_id FROM events")
def set_intersect_ids(spark, sf_dir):
    return table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("k")).intersect(table(spark, sf_dir, "events").select(F.col("user_id").alias("k")))


@query("SELECT o_custkey AS k FROM orders EXCEPT SELECT o_custkey FROM orders WHERE o_orderstatus = 'O'")
def set_except_ids(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    return o.select(F.col("o_custkey").alias("k")).subtract(o.where("o_orderstatus = 'O'").select(F.col("o_custkey").alias("k")))


# Functions.


@query("SELECT p_partkey, trim(lower(p_name)) AS name, substr(p_brand, 1, 4) AS head, lpad(p_size::VARCHAR, 4, '0') AS padded, levenshtein(p_name, p_brand)::INTEGER AS distance, translate(p_type, 'AEIOU', 'aeiou') AS vowels, length(p_name)::INTEGER AS n FROM part")
def fn_string_norm(spark, sf_dir):
    return table(spark, sf_dir, "part").select("p_partkey", F.trim(F.lower("p_name")).alias("name"), F.substring("p_brand", 1, 4).alias("head"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("padded"), F.levenshtein("p_name", "p_brand").alias("distance"), F.translate("p_type", "AEIOU", "aeiou").alias("vowels"), F.length("p_name").alias("n"))


@query("SELECT p_partkey, array_to_string(list_sort(list_distinct(list_transform(range(1, length(p_brand)), lambda i: substr(lower(p_brand), i, 2)))), ',') AS grams FROM part")
def fn_qgrams(spark, sf_dir):
    grams = F.transform(F.sequence(F.lit(1), F.length("p_brand") - 1), lambda i: F.substr(F.lower("p_brand"), i, F.lit(2)))
    return table(spark, sf_dir, "part").select("p_partkey", F.array_join(F.array_sort(F.array_distinct(grams)), ",").alias("grams"))


@query(f"SELECT c_custkey, md5(c_mktsegment) AS m, sha256(c_mktsegment) AS s, round({u('fn', 'c_custkey')}, 9) AS u FROM customer")
def fn_hash(spark, sf_dir):
    seg = F.col("c_mktsegment").cast("binary")
    return table(spark, sf_dir, "customer").select("c_custkey", F.md5(seg).alias("m"), F.sha2(seg, 256).alias("s"), F.round(rng.uniform(7, "fn", "c_custkey"), 9).alias("u"))


@query("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, date_trunc('month', o_orderdate)::DATE::VARCHAR AS m, (o_orderdate + INTERVAL 2 MONTH)::DATE::VARCHAR AS later, date_diff('day', DATE '1990-01-01', o_orderdate::DATE)::INTEGER AS days FROM orders")
def fn_dates_orders(spark, sf_dir):
    d = F.col("o_orderdate")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.year(d).alias("y"), F.to_date(F.date_trunc("month", d)).cast("string").alias("m"), F.add_months(F.to_date(d), 2).cast("string").alias("later"), F.datediff(F.to_date(d), F.lit("1990-01-01").cast("date")).alias("days"))


@query("SELECT i, round(-2.0 * sign(x - 0.5) * ln(1 - 2 * abs(x - 0.5)), 6) AS v FROM (SELECT c_custkey AS i, (c_custkey % 100 + 0.5) / 100.0::DOUBLE AS x FROM customer)")
def fn_laplace(spark, sf_dir):
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("i"), r6(rng.laplace((F.col("c_custkey") % 100 + 0.5) / 100.0, 2.0), "v"))


@query(f"SELECT c_custkey, round(x, 6) AS x, round({_erf('x')}, 6) AS erf FROM (SELECT c_custkey, (c_acctbal - 4500) / 1500 AS x FROM customer)")
def fn_erf(spark, sf_dir):
    """The error function of every customer's balance, centred and scaled to about -3.7 to 3.7."""
    return rounded(table(spark, sf_dir, "customer").select("c_custkey", ((F.col("c_acctbal") - 4500) / 1500).alias("x")).withColumn("erf", theory.erf(F.col("x"))))


@query("SELECT vec_id, list_sum(list_transform(embedding, lambda x: CASE WHEN x > 0 THEN 1 ELSE 0 END))::BIGINT AS positive, len(list_filter(embedding, lambda x: x > 0.1)) AS large, embedding[1] > embedding[2] AS falls FROM embeddings")
def fn_array_tokens(spark, sf_dir):
    e = F.col("embedding")
    return table(spark, sf_dir, "embeddings").select("vec_id", F.aggregate(F.transform(e, lambda x: (x > 0).cast("long")), F.lit(0).cast("long"), lambda a, x: a + x).alias("positive"), F.size(F.filter(e, lambda x: x > 0.1)).cast("long").alias("large"), (F.get(e, 0) > F.get(e, 1)).alias("falls"))


@query("SELECT nation.n_name, m.seg, m.n FROM (SELECT c_nationkey, c_mktsegment AS seg, count(*) AS n FROM customer GROUP BY ALL) m JOIN nation ON n_nationkey = c_nationkey")
def fn_map_json(spark, sf_dir):
    """Counts packed to a map, to JSON and back."""
    counts = table(spark, sf_dir, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))
    packed = counts.groupBy("c_nationkey").agg(F.to_json(F.map_from_entries(F.collect_list(F.struct("c_mktsegment", "n")))).alias("j"))
    back = packed.select("c_nationkey", F.explode(F.from_json("j", "map<string,bigint>")).alias("seg", "n"))
    return back.join(F.broadcast(table(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("n_name", "seg", "n")


# SQL surface.


@query("WITH m AS (SELECT avg(c_acctbal) AS a FROM customer) SELECT c_custkey FROM customer c WHERE c_acctbal > (SELECT a FROM m) AND EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 1000) AND c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)")
def sql_subquery_rates(spark, sf_dir):
    for name in ("customer", "orders", "nation"):
        table(spark, sf_dir, name).createOrReplaceTempView(f"fl_{name}")
    return spark.sql("WITH m AS (SELECT avg(c_acctbal) AS a FROM fl_customer) SELECT c_custkey FROM fl_customer c WHERE c_acctbal > (SELECT a FROM m) AND EXISTS (SELECT 1 FROM fl_orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 1000) AND c_nationkey IN (SELECT n_nationkey FROM fl_nation WHERE n_regionkey = 1)")


@query("SELECT c_custkey, round(CASE WHEN bit_count(c_custkey) + bit_count(c_nationkey::BIGINT) = 0 THEN 0 ELSE 2.0 * bit_count(c_custkey & c_nationkey::BIGINT) / (bit_count(c_custkey) + bit_count(c_nationkey::BIGINT)) END, 6) AS dice FROM (SELECT c_custkey::BIGINT AS c_custkey, c_nationkey FROM customer)")
def sql_dice(spark, sf_dir):
    sqlfun.register(spark)
    table(spark, sf_dir, "customer").createOrReplaceTempView("fl_customer")
    return spark.sql("SELECT CAST(c_custkey AS BIGINT) AS c_custkey, round(fl_dice(CAST(c_custkey AS BIGINT), CAST(c_nationkey AS BIGINT)), 6) AS dice FROM fl_customer")


@query("SELECT p_partkey, substr(lower(p_brand), i, 2) AS token FROM part, unnest(range(1, length(p_brand))) u(i)")
def udtf_tokens(spark, sf_dir):
    sqlfun.register(spark)
    table(spark, sf_dir, "part").createOrReplaceTempView("fl_part")
    return spark.sql("SELECT p_partkey, t.token FROM fl_part, LATERAL fl_tokens(p_brand, 2) t")


@query("SELECT c_mktsegment, round(quantile_cont(c_acctbal, 0.5), 6) AS median, round(quantile_cont(c_acctbal, 0.9), 6) AS upper FROM customer GROUP BY ALL")
def udaf_quantiles(spark, sf_dir):
    """Exact quantiles of a group by the built-in aggregate, which counts equal values."""
    return rounded(table(spark, sf_dir, "customer").groupBy("c_mktsegment").agg(F.percentile("c_acctbal", 0.5).alias("median"), F.percentile("c_acctbal", 0.9).alias("upper")))


@query()
def ml_logistic(spark, sf_dir):
    """A logistic model of the toxic label by text length and language, and its area under the curve."""
    from pyspark.ml.evaluation import BinaryClassificationEvaluator

    from fairlink.operators import classify

    rows = table(spark, sf_dir, "labels").join(table(spark, sf_dir, "documents"), "doc_id").select("doc_id", (F.col("toxic") == 1).alias("truth"), F.ln(F.col("n_chars") + 1.0).alias("size"), (F.col("lang") == "en").cast("double").alias("english"))
    train, test = classify.split(rows, key="doc_id")
    fitted = classify.model("logistic", train, ["size", "english"])
    judged = classify.predict(fitted, test, ["size", "english"])
    area = BinaryClassificationEvaluator(rawPredictionCol="score", labelCol="label").evaluate(judged.withColumn("label", F.col("truth").cast("double")))
    return spark.createDataFrame([(float(area),)], "area double")


# Streams: batch equivalents are the oracles.


@query("SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_bins_tumbling(spark, sf_dir):
    return bins.windowed(spark, f"{sf_dir}/events.parquet", "1 day")


@query("SELECT start, event_type, count(*) AS n FROM (SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') - to_hours(12 * k) + CASE WHEN k = 1 AND ts - time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01') >= INTERVAL 12 HOUR THEN INTERVAL 24 HOUR ELSE INTERVAL 0 HOUR END AS start, event_type FROM events, range(2) r(k)) GROUP BY ALL")
def stream_sliding(spark, sf_dir):
    return bins.windowed(spark, f"{sf_dir}/events.parquet", "1 day", "12 hours")


@query("SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > ts - INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def stream_session(spark, sf_dir):
    return bins.sessions(spark, f"{sf_dir}/events.parquet", "6 hours")


@query("SELECT event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_dedup(spark, sf_dir):
    return bins.deduplicated(spark, f"{sf_dir}/events.parquet")


@query("SELECT c_custkey, count(*) AS n FROM customer JOIN events ON user_id = c_custkey GROUP BY ALL")
def stream_link(spark, sf_dir):
    return bins.linked(spark, f"{sf_dir}/events.parquet", table(spark, sf_dir, "customer").select("c_custkey"))


@query()
def stream_noisy_counts(spark, sf_dir):
    return bins.noisy(spark, f"{sf_dir}/events.parquet", "1 day", 1.0)


@query()
def hot_bins_split(spark, sf_dir):
    """Largest bin before and after hot bins are split by further label bits."""
    from fairlink.operators import encode
    from fairlink.settings import DEFAULT

    blocked = block.bit_labels(encode.encoded(people.parties(spark, sf_dir)))
    size = lambda df: df.groupBy("party", *block.BIN).agg(F.count("*").alias("n")).agg(F.max("n").alias("largest"))
    return size(blocked).select(F.lit("before").alias("when"), "largest").unionByName(size(block.hot_bins(blocked, DEFAULT, 10)).select(F.lit("after").alias("when"), "largest"))
