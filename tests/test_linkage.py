import hashlib
from collections import Counter

import pytest
from fairlink.functions import bits, rng, tokens
from fairlink.operators import block, classify, corrupt, encode, joins, measures, noise, pairs
from fairlink.plans import scenarios
from fairlink.settings import DEFAULT
from fairlink.sources import people
from fairlink.sources.tables import PartySource
from pyspark.sql import functions as F


def big(row, prefix="w"):
    return sum(row[f"{prefix}{i}"] << (60 * i) for i in range(5))


@pytest.fixture(scope="module")
def bench(spark, small):
    b = scenarios.bench(spark, small)
    return scenarios.Bench(b.blocked.cache(), b.stats.cache(), b.truth.cache(), b.settings)


def test_keyed_draw_is_the_known_one(spark):
    assert spark.range(1).select(rng.whole(F.lit("7|noise|12|g1")).alias("x")).first()["x"] == 3418281203565556


def test_tokens(spark):
    row = spark.sql("SELECT 'O''Brien' AS a, '' AS b, CAST(NULL AS STRING) AS c, 'x' AS d, 'Müller' AS e").select(*[tokens.qgrams(F.col(c), "p:").alias(c) for c in "abcde"], tokens.exact(F.col("c"), "p:").alias("f")).first()
    assert row["a"] == ["p:ob", "p:br", "p:ri", "p:ie", "p:en"]
    assert row["b"] == row["c"] == row["f"] == []
    assert row["d"] == ["p:x"]
    assert row["e"][0] == "p:mü"


def test_filters_against_big_integers(spark, small):
    rows = encode.bloom(people.parties(spark, small), encode.voter_tokens()).withColumn("t", encode.voter_tokens()).limit(20).collect()
    for r in rows:
        want = 0
        for t in r["t"]:
            code = hashlib.md5(f"shared|{t}".encode()).hexdigest()
            a, b = int(code[:13], 16), int(code[13:26], 16)
            for i in range(DEFAULT.k_hash):
                want |= 1 << ((a + i * b) % 300)
        assert big(r) == want and r["n_ones"] == want.bit_count()


def test_labels_are_the_sampled_bits(bench):
    for r in bench.blocked.limit(30).collect():
        want = sum(((big(r) >> p) & 1) << j for j, p in enumerate(DEFAULT.label_positions(r["table_no"])))
        assert r["label"] == want


def test_candidates_are_all_pairs_of_equal_labels_once(bench):
    rows = {r["rec_id"]: r for r in bench.blocked.where("table_no = 0").collect()}
    want = set()
    for x in rows.values():
        for y in rows.values():
            if x["party"] == "A" and y["party"] == "B" and x["group_id"] == y["group_id"] and any(x[f"l{t}"] == y[f"l{t}"] for t in range(5)):
                want.add((x["rec_id"], y["rec_id"]))
    found = scenarios.plain_pairs(bench).collect()
    assert len(found) == len(want) and {(r["id_a"], r["id_b"]) for r in found} == want
    for r in found:
        x, y = rows[r["id_a"]], rows[r["id_b"]]
        assert r["sim"] == pytest.approx(2 * (big(x) & big(y)).bit_count() / (x["n_ones"] + y["n_ones"]))


def test_dice_of_hand_made_filters(spark):
    def row(i, word, party):
        return (party, i, 0, "g", *([word] + [0] * 4), word.bit_count(), 0, 0)

    names = ["party", "rec_id", "entity_id", "group_id", *bits.names(), "n_ones", "table_no", "label"]
    rows = spark.createDataFrame([row("a1", 15, "A"), row("a2", 0, "A"), row("b1", 15, "B"), row("b2", 240, "B"), row("b3", 51, "B"), row("b4", 0, "B")], names)
    sims = {(r["id_a"], r["id_b"]): r["sim"] for r in pairs.candidates(*pairs.split(rows)).collect()}
    assert sims[("a1", "b1")] == 1 and sims[("a1", "b2")] == 0 and sims[("a1", "b3")] == 0.5 and sims[("a2", "b4")] == 0
    assert pairs.candidates(*pairs.split(rows), least=0.8).count() == 3  # filters with as many ones; the empty ones go
    assert classify.threshold(pairs.candidates(*pairs.split(rows)), 1.0).where("pred").count() == 0


def knobs(spark, eps=2.0, flip=0.4):
    return spark.createDataFrame([("m", eps, flip), ("w", eps, flip)], "group_id string, eps double, flip double")


def test_dummies_stay_in_bounds_and_bins(spark, bench):
    counts = noise.dummy_counts(bench.stats, knobs(spark, 0.2))
    assert counts.where("m < 0 OR m > n").count() == 0
    noisy = noise.feature_dp(bench.blocked, knobs(spark, 0.2)).cache()
    assert noisy.where("NOT is_dummy").count() == bench.blocked.count()
    made = noisy.where("is_dummy").groupBy(*noise.KEYS).agg(F.count("*").alias("k"))
    assert counts.where("m > 0").join(made, noise.KEYS, "full").where("NOT (m <=> k)").count() == 0
    assert set(noise.opaque(noisy).columns).isdisjoint({"entity_id", "is_dummy", "parent_id"})


def test_flip_borders(spark, bench):
    for flip, check in ((0.0, "="), (1.0, "!")):
        made = noise.feature_dp(bench.blocked, knobs(spark, 0.2, flip)).where("is_dummy").alias("d")
        source = bench.blocked.where("table_no = 0").alias("s")
        rows = made.join(source, F.col("d.parent_id") == F.col("s.rec_id")).select(*[F.col(f"d.w{i}").alias(f"d{i}") for i in range(5)], *[F.col(f"s.w{i}").alias(f"s{i}") for i in range(5)]).collect()
        assert rows
        for r in rows:
            assert big(r, "d") == (big(r, "s") if check == "=" else big(r, "s") ^ ((1 << 300) - 1))


def test_noise_does_not_depend_on_partitions(spark, bench):
    one = noise.dummy_counts(bench.stats.repartition(1), knobs(spark)).select(*noise.KEYS, "m")
    many = noise.dummy_counts(bench.stats.repartition(16), knobs(spark)).select(*noise.KEYS, "m")
    assert one.exceptAll(many).count() == 0


def test_geometric_noise_on_neighbours(spark):
    draws = spark.range(20_000).select(rng.geometric(rng.uniform(1, "a", "id"), rng.uniform(1, "b", "id"), 1.0).alias("x"))
    seen = {r["x"]: r["count"] for r in draws.groupBy("x").count().collect()}
    for x in (-2, -1, 0, 1):
        assert seen[x] / seen[x + 1] < 2.718281828 * 1.15 and seen[x + 1] / seen[x] < 2.718281828 * 1.15


def test_swapping_an_unmatched_record_keeps_the_links(spark, small, bench):
    truth = {r["id_b"] for r in bench.truth.collect()}
    lonely = bench.blocked.where("party = 'B' AND table_no = 0").where(~F.col("rec_id").isin(list(truth))).select("rec_id").first()["rec_id"]
    links = lambda rows: {(r["id_a"], r["id_b"]) for r in classify.threshold(pairs.candidates(*pairs.split(rows)), 0.95).where("pred").collect()}
    assert {x for x in links(bench.blocked) if x[1] != lonely} == links(bench.blocked.where(F.col("rec_id") != lonely))


def test_measures_by_hand(spark):
    rows = spark.createDataFrame([("m", True, True)] * 3 + [("m", True, False)] + [("m", False, False)] * 3 + [("w", False, True)] + [("w", True, True)], "group_id string, pred boolean, truth boolean")
    r = {x["group_id"]: x for x in measures.rates(measures.confusion(rows)).collect()}
    assert (r["m"]["fpr"], r["m"]["recall"], r["m"]["fstar"]) == (0.25, 1.0, 0.75)
    assert (r["w"]["fnr"], r["w"]["precision"]) == (0.5, 1.0)
    f = measures.fairness(measures.rates(measures.confusion(rows))).first()
    assert f["loss"] == 0.5 and f["fairness"] == 0.5


def test_cost_without_the_join_is_the_join_size(spark, bench):
    noisy = noise.feature_dp(bench.blocked, knobs(spark))
    counts = noise.dummy_counts(bench.stats, knobs(spark))
    every = pairs.candidates(*pairs.split(noisy), first_table_only=False)
    want = {r["group_id"]: r["count"] for r in every.groupBy("group_id").count().collect()}
    assert {r["group_id"]: r["pairs"] for r in measures.cost(counts).collect()} == want


def test_edits_change_half_of_the_rows(spark, small):
    a = people.parties(spark, small).where("party = 'B'").select("entity_id", "given", "surname", "suburb", "postcode")
    b = people.parties(spark, small, "dirty").where("party = 'B'").select("entity_id", "given", "surname", "suburb", "postcode")
    share = a.exceptAll(b).count() / a.count()
    assert 0.25 < share < 0.65
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "x")], "entity_id long, name string")
    assert corrupt.edits(odd, ["name"], 1.0, 3).count() == 3


def test_odd_people(spark):
    odd = spark.createDataFrame([("A", "a", 1, "g", None, "", "é", "1", "m"), ("B", "b", 1, "g", None, None, None, None, "m")], "party string, rec_id string, entity_id long, group_id string, given string, surname string, suburb string, postcode string, gender string")
    rows = block.bit_labels(encode.encoded(odd))
    assert rows.count() == 10
    empty = rows.where("party = 'C'")
    assert pairs.candidates(rows, empty).count() == 0
    assert noise.feature_dp(empty, knobs(spark)).count() == 0


def test_as_of_takes_the_last_value(spark):
    a = spark.createDataFrame([(1, 5, "x"), (1, 1, "y"), (2, 9, "z")], "k int, at int, n string")
    b = spark.createDataFrame([(1, 2, 20), (1, 5, 50), (2, 10, 100)], "k int, at int, v int")
    assert {r["n"]: r["v"] for r in joins.as_of(a, b, "k", "at", ["v"]).collect()} == {"x": 50, "y": None, "z": None}


def test_party_source(spark):
    spark.dataSource.register(PartySource)
    rows = spark.read.format("party").option("rows", 25).option("perpartition", 10).load()
    assert rows.count() == 25 and rows.rdd.getNumPartitions() == 3


def test_no_python_and_no_cartesian_product_in_the_pair_plan(bench):
    plan = scenarios.plain_pairs(bench)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "EvalPython" not in plan and "MapIn" not in plan


def test_many_runs_are_the_single_ones(spark, bench):
    runs = [scenarios.Run("b1"), scenarios.Run("b2", 0.2, 0.3), scenarios.Run("b2", 1.0, 0.0), scenarios.Run("b3", 0.5)]
    counts = {(r["scenario"], r["eps"], r["group_id"]): (r["tp"], r["fp"], r["tn"], r["fn"]) for r in scenarios.grid(spark, "", runs, b=bench).collect()}
    single = {
        ("b1", 1.0): bench.blocked.withColumn("is_dummy", F.lit(False)),
        ("b2", 0.2): noise.feature_dp(bench.blocked, knobs(spark, 0.4, 0.3)),
        ("b2", 1.0): noise.feature_dp(bench.blocked, knobs(spark, 2.0, 0.0)),
        ("b3", 0.5): noise.record_dp(bench.blocked, 0.5, 0.4),
    }
    for (name, eps), rows in single.items():
        for r in measures.confusion(classify.threshold(pairs.candidates(*pairs.split(rows))), bench.truth).collect():
            assert counts[name, eps, r["group_id"]] == (r["tp"], r["fp"], r["tn"], r["fn"])


def test_learners_are_judged_on_other_records(spark, small):
    b = scenarios.bench(spark, small, "dirty", keep=True, attributes=True)
    own = scenarios.plain_pairs(b)
    assert scenarios.features_of(b) == ["sim0", "sim1", "sim2", "sim3", "sim4", "sim"] and set(scenarios.features_of(b)) <= set(own.columns)
    judged = own.where(scenarios.tested()).select("id_a").distinct()
    assert own.where(~scenarios.tested()).join(judged, "id_a").count() == 0
    counts = scenarios.grid(spark, small, [scenarios.Run("b1"), scenarios.Run("b2", 0.2)], "dirty", classifiers=("logistic",), b=b).collect()
    half = b.truth.withColumn("source_a", F.col("id_a")).where(scenarios.tested()).count()
    assert sum(r["tp"] + r["fn"] for r in counts if r["scenario"] == "b1") == half


def test_padded_bins(spark, bench):
    rows = noise.padded(bench.blocked, 4, 0.3)
    sizes = rows.groupBy("party", *block.BIN).agg(F.count("*").alias("n"), F.count_if(~F.col("is_dummy")).alias("own"))
    assert sizes.where("n <> greatest(own, 4)").count() == 0
    made = rows.where("is_dummy")
    assert made.select("rec_id", "table_no").distinct().count() == made.count()


def test_tiles_hold_every_pair_once(spark, bench):
    rows = bench.blocked.where("table_no = 0").select("party", "rec_id", "entity_id", "group_id", *bits.names(), "n_ones")
    found = pairs.candidates(*pairs.split(block.tiles(rows, 3)), scope="all")
    sides = {r["party"]: r["count"] for r in rows.groupBy("party").count().collect()}
    assert found.count() == found.select("id_a", "id_b").distinct().count() == sides["A"] * sides["B"]


def test_near_labels_by_brute_force(spark, bench):
    rows = {r["rec_id"]: r for r in bench.blocked.where("table_no = 0").collect()}
    near = lambda x, y: any((x[f"l{t}"] ^ y[f"l{t}"]).bit_count() <= 1 for t in range(5))
    want = {(x["rec_id"], y["rec_id"]) for x in rows.values() for y in rows.values() if x["party"] == "A" and y["party"] == "B" and x["group_id"] == y["group_id"] and near(x, y)}
    found = pairs.near_candidates(*pairs.split(bench.blocked), block.near_labels(bench.stats, DEFAULT.label_bits)).collect()
    assert len(found) == len(want) and {(r["id_a"], r["id_b"]) for r in found} == want


def test_ratio_of_neighbours_stays_near_the_bound(spark):
    for r in noise.empirical_ratio(spark, 20, 1.0, 20_000).where("own > 800 AND neighbour > 800").collect():
        assert 1 / (r["bound"] * 1.15) < r["ratio"] < r["bound"] * 1.15


def test_bucketed_sink_joins_without_exchange(spark, bench, tmp_path):
    spark.sql(f"CREATE DATABASE IF NOT EXISTS fl LOCATION '{tmp_path}/fl'")
    for p in ("A", "B"):
        bench.blocked.where(F.col("party") == p).write.mode("overwrite").bucketBy(4, *block.BIN, "group_id").format("parquet").saveAsTable(f"fl.side_{p.lower()}")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        a, b = spark.table("fl.side_a"), spark.table("fl.side_b")
        plan = pairs.candidates(a, b)._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan
        assert pairs.candidates(a, b).count() == scenarios.plain_pairs(bench).count()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP DATABASE fl CASCADE")


def test_equal_census_records_are_compared_once(spark, small):
    """Kinds of equal records stand for all pairs of records, half by half, with far fewer rows; so do their dummies' pairs."""
    from dataclasses import replace

    from fairlink.plans import scenarios

    b = scenarios.bench(spark, small, "census", keep=True, attributes=True)
    keys = ["group_id", "half", "truth", *scenarios.features_of(b)]
    kinds, single = scenarios.kind_pairs(b), scenarios.half(scenarios.plain_pairs(b))
    want = Counter(tuple(r) for r in single.select(*keys).collect())
    found = {tuple(r)[:-1]: r["copies"] for r in kinds.select(*keys, "copies").collect()}
    assert found == want and len(found) < 0.7 * sum(want.values())
    runs = [scenarios.Run("b1"), scenarios.Run("b2", 0.1)]
    both = [sorted(map(tuple, scenarios.grid(spark, small, runs, "census", classifiers=("threshold", "logistic"), b=replace(b, alike=alike)).collect())) for alike in (True, False)]
    assert both[0] == both[1]


def test_tiles_are_the_pair_join(spark, small, monkeypatch):
    """Passes over tiles, of several blocks a bin, count and train as the pairs of the join do; learners write no pairs."""
    from fairlink.operators import tiles

    b = scenarios.bench(spark, small, "dirty", keep=True, attributes=True)
    made, own = scenarios.tiled(b), scenarios.plain_pairs(b)
    assert sorted(scenarios.threshold_counts(b, made).collect()) == sorted(measures.confusion(classify.threshold(own)).collect())
    monkeypatch.setattr(tiles, "CHUNK", 7)
    train = classify.group_weights(scenarios.half(own).where("NOT half"), ["truth", "group_id"])
    model, beta = classify.model("logistic", train, scenarios.features_of(b), weight="weight"), tiles.logistic(made, 5, 5, True)
    assert [beta[0], *beta[1:]] == pytest.approx([model.intercept, *model.coefficients], abs=1e-3)
    monkeypatch.setattr(scenarios, "plain_pairs", None)
    counts = scenarios.grid(spark, small, [scenarios.Run("b1")], "dirty", classifiers=("logistic",), b=b).select("group_id", "tp", "fp", "tn").collect()
    want = measures.confusion(classify.predict(model, scenarios.half(own).where("half"), scenarios.features_of(b))).select("group_id", "tp", "fp", "tn").collect()
    assert sorted(counts) == sorted(want)


def test_values_are_hashed_once(spark, small):
    rows = people.parties(spark, small, "dirty")
    for rounds, attributes in ((1, True), (2, False)):
        every, once = encode.encoded(rows, rounds=rounds, attributes=attributes), encode.encoded_values(rows, rounds=rounds, attributes=attributes)
        assert once.count() == every.count() and every.exceptAll(once.select(*every.columns)).count() == 0


def test_sweep_counts_originals_once(spark, small, monkeypatch):
    runs = {"names": ("b1", "b2"), "eps": (1.0,), "seeds": (7, 8)}
    want = [tuple(r) for r in scenarios.summaries(scenarios.grid(spark, small, [scenarios.Run("b1")])).select("fpr", "recall", "comparisons").collect()]
    monkeypatch.setattr(scenarios, "plain_pairs", None)
    assert [tuple(r) for r in scenarios.sweep(spark, small, **runs).where("scenario = 'b1'").select("fpr", "recall", "comparisons").collect()] == want


def test_trees_of_cells_are_those_of_pairs(spark, small, monkeypatch):
    """A tree of cells is that of Spark's learner on single pairs; neither it nor a forest writes a pair."""
    from fairlink.operators import cells

    b = scenarios.bench(spark, small, "dirty", keep=True, attributes=True)
    own = scenarios.half(scenarios.plain_pairs(b)).cache()
    model = classify.model("tree", own.where("NOT half"), scenarios.features_of(b))
    want = sorted(measures.confusion(classify.predict(model, own.where("half"), scenarios.features_of(b))).select("group_id", "tp", "fp", "tn").collect())
    monkeypatch.setattr(scenarios, "plain_pairs", None)
    monkeypatch.setattr(cells, "CHUNK", 7)
    counts = {kind: scenarios.grid(spark, small, [scenarios.Run("b1")], "dirty", classifiers=(kind,), b=b).select("group_id", "tp", "fp", "tn", "real").collect() for kind in ("tree", "forest")}
    assert sorted(tuple(r)[:4] for r in counts["tree"]) == [tuple(r) for r in want]
    every, true = own.where("half").count(), own.where("half AND truth").count()
    assert sum(r["real"] for r in counts["forest"]) == every and sum(r["tp"] for r in counts["forest"]) >= 0.8 * true
    grid, leaves = cells.fitted(scenarios.tiled(b), 5, 5, 3)
    found, single = tiles_judged(scenarios.tiled(b), grid, leaves), measures.confusion(cells.scored(own.where("half"), grid, leaves, scenarios.features_of(b)))
    assert sorted(found.collect()) == sorted(single.collect())


def test_support_vectors_of_tiles_are_those_of_pairs(spark, small, monkeypatch):
    """The classifier of tiles has the least loss on single pairs, from however poor a start, and Spark's verdicts; it writes no pair."""
    from dataclasses import replace

    import numpy as np
    from fairlink.operators import hinge, tiles

    b = scenarios.bench(spark, small, "dirty", keep=True, attributes=True)
    own = scenarios.half(scenarios.plain_pairs(b)).cache()
    names = scenarios.features_of(b)
    model = classify.model("svm", own.where("NOT half"), names)
    rows = own.where("NOT half").select(*names, "truth").toPandas()
    x, y = rows[names].to_numpy(), np.where(rows["truth"], 1.0, -1.0)

    def loss(beta):
        return np.maximum(0.0, 1 - y * (beta[0] + x @ beta[1:])).mean() + 0.5e-3 * (x.var(0, ddof=1) * beta[1:] ** 2).sum()

    made = scenarios.tiled(b)
    whole = hinge.fitted(made, 5, 5)
    for name, value in (("NEAR", 0), ("LEAST", 0), ("FLUSH", 6)):
        monkeypatch.setattr(hinge, name, value)
    monkeypatch.setattr(tiles, "CHUNK", 7)
    passes, read = [], hinge._beyond
    monkeypatch.setattr(hinge, "_beyond", lambda *x: passes.append(x) or read(*x))
    few = hinge.fitted(made, 5, 5, start=8)
    assert len(passes) >= 2
    assert loss(whole) <= loss(np.array([model.intercept, *model.coefficients])) and loss(few) == pytest.approx(loss(whole), rel=1e-3)
    none = replace(b, blocked=b.blocked.withColumn("entity_id", F.lit(None).cast("long")))
    assert hinge.fitted(scenarios.tiled(none), 5, 5).tolist() == [-1.0] + [0.0] * 6
    want = measures.confusion(classify.predict(model, own.where("half"), names)).select("group_id", "tp", "fp", "tn").collect()
    monkeypatch.setattr(scenarios, "plain_pairs", None)
    counts = scenarios.grid(spark, small, [scenarios.Run("b1")], "dirty", classifiers=("svm",), b=b).select("group_id", "tp", "fp", "tn").collect()
    assert sorted(counts) == sorted(want)


def tiles_judged(made, grid, leaves):
    from fairlink.operators import cells, tiles

    return tiles.judged(made, 5, 5, cells.Verdict(grid, leaves), half=True, reader=cells.Reader(grid))


def test_all_pairs_by_bounds_are_the_pair_join(spark, small, monkeypatch):
    """Bounds lose no pair, whatever records are put together, with copies, in several cells, at any threshold; the query writes no pair."""
    from fairlink.operators import allpairs
    from fairlink.plans import methods

    rows = encode.encoded_values(people.parties(spark, small), more=("suburb", "surname", "area"))
    rows = rows.union(rows.where("entity_id % 3 = 0")).cache()
    monkeypatch.setattr(allpairs, "MOST", 40)
    monkeypatch.setattr(allpairs, "TOGETHER", 3)
    every = pairs.candidates(*pairs.split(block.none(rows))).cache()
    for t, together in ((0.8, ["suburb", "surname"]), (0.55, ["suburb"]), (0.6, ["area"])):
        want = sorted(tuple(r) for r in measures.confusion(classify.threshold(every, t)).collect())
        assert sorted(tuple(r) for r in allpairs.counts(rows, every.where("truth"), t, together).collect()) == want
    whole = pairs.candidates
    monkeypatch.setattr(pairs, "candidates", lambda *x, entities=False, **more: whole(*x, entities=entities, **more) if entities else None)
    assert methods.scenario_all_pairs(spark, small).count() == 2
