"""The experiments: scenarios by budget and classifier, curves, costs, and comparisons with other ways of blocking."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fairlink.functions import theory
from fairlink.operators import block, classify, encode, measures, noise, pairs
from fairlink.plans import scenarios
from fairlink.plans.methods import _AGE, _BIASED, _DIRTY, _FLIPS, _RECS, _edit_sql
from fairlink.plans.oracle import CENSUS, COMMON, EARLIER, ONES, RATES, STEPS, SUMMARY, TOKENS, _conf, _erf, encoded, false_match, label, rate, runs_sql, sql, u
from fairlink.plans.registry import query, rounded
from fairlink.plans.scenarios import Run
from fairlink.settings import DEFAULT
from fairlink.sources import people
from fairlink.sources.steps import written
from fairlink.sources.tables import table

BUDGETS = (0.1, 1.0, 10.0)
SHOWN = ["scenario", "eps", "fpr", "recall", "precision", "fstar", "loss", "fairness", "comparisons", "fake"]
_DIRTY_AGE = _RECS.format(group=_AGE, change="REPLACE (" + ", ".join(_edit_sql(c, i) for i, c in enumerate(("given", "surname", "suburb", "postcode"))) + ")")
_CENSUS = f"SELECT *, ({ONES})::INTEGER AS n_ones FROM ({encoded('recs', CENSUS)})"


def four(budgets=BUDGETS) -> list[Run]:
    """No noise, equal knobs, tuned flips and tuned budgets."""
    return [Run("b1"), *(Run(n, e) for n in ("b2", "a", "b") for e in budgets)]


def _grid(spark, sf_dir, classifier, budgets=BUDGETS, **options) -> DataFrame:
    return rounded(scenarios.summaries(scenarios.grid(spark, sf_dir, four(budgets), classifiers=(classifier,), **options)).select(*SHOWN))


# Fairness and F* of four scenarios by budget.


@query(runs_sql(SUMMARY, four()))
def grid_clean_gender(spark, sf_dir):
    return _grid(spark, sf_dir, "threshold")


@query(runs_sql(SUMMARY, four(), recs=_DIRTY))
def grid_dirty_gender(spark, sf_dir):
    return _grid(spark, sf_dir, "threshold", flavour="dirty")


@query(runs_sql(SUMMARY, four(), recs=_DIRTY_AGE))
def grid_dirty_age(spark, sf_dir):
    return _grid(spark, sf_dir, "threshold", flavour="dirty", features=("age_band",))


@query(runs_sql(SUMMARY, four(), recs=_BIASED))
def grid_biased_gender(spark, sf_dir):
    return _grid(spark, sf_dir, "threshold", flavour="biased")


@query(runs_sql(SUMMARY, four((0.1, 1.0)), enc=_CENSUS))
def grid_census_gender(spark, sf_dir):
    return _grid(spark, sf_dir, "threshold", (0.1, 1.0), flavour="census")


@query()
def grid_clean_gender_logistic(spark, sf_dir):
    return _grid(spark, sf_dir, "logistic")


@query()
def grid_dirty_gender_logistic(spark, sf_dir):
    return _grid(spark, sf_dir, "logistic", flavour="dirty")


@query()
def grid_dirty_age_logistic(spark, sf_dir):
    return _grid(spark, sf_dir, "logistic", flavour="dirty", features=("age_band",))


@query()
def grid_census_gender_logistic(spark, sf_dir):
    return _grid(spark, sf_dir, "logistic", (0.1, 1.0), flavour="census")


@query()
def sweep_scenarios(spark, sf_dir):
    """All scenarios on clean and biased records, averaged over three seeds of the noise."""
    return rounded(scenarios.sweep(spark, sf_dir, eps=(1.0,), flavours=("clean", "biased"), seeds=(7, 8, 9)))


# Curves: prediction beside measurement.


def rising() -> list[Run]:
    return [Run("b2", e, f) for f in (0.4, 0.7, 1.0) for e in (0.1, 0.2, 0.5, 1.0, 2.0, 5.0, 10.0)]


def _predicted(counts: DataFrame, sizes: DataFrame, plain: DataFrame) -> DataFrame:
    """Per run and group the measured rate and fake pairs beside the predicted ones, and the errors of prediction."""
    known = counts.join(F.broadcast(sizes), "group_id").join(F.broadcast(plain), "group_id")  # one row a group
    f, eps = F.col("flip"), 2 * F.col("eps")
    p = F.when(f >= 1, 0.0).otherwise(0.5 * (1 - theory.erf((240.0 * f / (2 * (1 - 0.8) * F.nullif(1 - f, F.lit(0.0))) - 150) / F.sqrt(F.lit(150.0)))))
    fake = (F.col("na") + F.col("nb")) / eps / 2 + F.col("bins") / eps / eps / 4
    measured, predicted = measures.ratio(F.col("fp"), F.col("fp") + F.col("tn")), (p * fake + F.col("ofp")) / (fake + F.col("ofp") + F.col("otn"))
    return known.select("flip", "eps", "group_id", measured.alias("fpr"), predicted.alias("predicted_fpr"), (predicted - measured).alias("fpr_error"), F.col("fake"), fake.alias("predicted_fake"), (fake - F.col("fake")).alias("fake_error"))


def _curve_eps(spark, sf_dir, classifier: str) -> DataFrame:
    b = scenarios.bench(spark, sf_dir, keep=True, attributes=classifier != "threshold")
    counts = scenarios.grid(spark, sf_dir, [Run("b1"), *rising()], classifiers=(classifier,), b=b)
    kept = written(counts, "curve")
    plain = kept.where("scenario = 'b1'").select("group_id", F.col("fp").alias("ofp"), F.col("tn").alias("otn"))
    return rounded(_predicted(kept.where("scenario = 'b2'"), scenarios.group_sizes(b), plain))


_EXPECTED = "((na + nb) / (2 * c.eps) / 2 + bins / (2 * c.eps) / (2 * c.eps) / 4)"
_FPR = "(CASE WHEN c.fp + c.tn = 0 THEN 0.0 ELSE c.fp / (c.fp + c.tn)::DOUBLE END)"
_P_FPR = f"(({false_match('c.flip')} * {_EXPECTED} + g.fp) / ({_EXPECTED} + neg))"


@query(runs_sql(f"SELECT c.flip, c.eps, c.group_id, round({_FPR}, 6) AS fpr, round({_P_FPR}, 6) AS predicted_fpr, round({_P_FPR} - {_FPR}, 6) + 0::DOUBLE AS fpr_error, c.fake, round({_EXPECTED}, 6) AS predicted_fake, round({_EXPECTED} - c.fake, 6) + 0::DOUBLE AS fake_error FROM cells c JOIN gst g USING (group_id)", rising()))
def curve_fpr_eps(spark, sf_dir):
    """False-positive rate over budgets for three clean flips, threshold classifier."""
    return _curve_eps(spark, sf_dir, "threshold")


@query()
def curve_fpr_eps_logistic(spark, sf_dir):
    """The same with the logistic classifier, on the test half; predicted fake pairs are of all records."""
    return _curve_eps(spark, sf_dir, "logistic")


_HALF = STEPS["recs"].replace("FROM people WHERE", f"FROM people WHERE {u('share', 'entity_id')} < 0.5 AND")
_DRAWS = f"""SELECT rec_id, table_no, n_ones, (CASE bit // 60 {' '.join(f'WHEN {i} THEN w{i}' for i in range(5))} END >> (bit % 60)::INTEGER) & 1 AS one,
    (('0x' || substr(md5('{DEFAULT.seed}|flip|' || rec_id || '|' || table_no::VARCHAR || '|' || (bit // 60)::VARCHAR || '|' || (bit % 60 // 2)::VARCHAR), CASE bit % 2 WHEN 0 THEN 1 ELSE 14 END, 13))::BIGINT + 0.5) / 4503599627370496.0 AS d FROM chosen, range(300) r(bit)"""
_KEPT = "(n_ones - coalesce(sum(one) FILTER (WHERE d < flip), 0))"
_MEASURED = f"""SELECT flip, count(*) AS dummies, avg(CASE WHEN 2.0 * kept / (n_ones + kept + added) > 0.8 THEN 1.0 ELSE 0.0 END) AS measured
    FROM (SELECT rec_id, table_no, flip, n_ones, {_KEPT} AS kept, coalesce(sum(1 - one) FILTER (WHERE d < flip), 0) AS added FROM draws, (SELECT f / 50.0::DOUBLE AS flip FROM range(51) r(f)) GROUP BY rec_id, table_no, flip, n_ones) GROUP BY flip"""
_NORMAL = f"(CASE WHEN cut IS NULL THEN 0.0 ELSE 0.5 * (1 - {_erf('((cut - 150) / sqrt(150.0::DOUBLE))')}) END)"


@query(sql(f"SELECT flip, dummies, round(measured, 6) AS measured, round({_NORMAL}, 6) AS normal, round({_NORMAL} - measured, 6) + 0::DOUBLE AS error FROM measured JOIN {_FLIPS} USING (flip)", "chosen", recs=_HALF, draws=_DRAWS, measured=_MEASURED))
def curve_dummy_fp(spark, sf_dir):
    """Chance of a dummy's false match over flips 0, 0.02, .., 1 on the smaller pair of parties: measured, predicted, error."""
    found = scenarios.dummy_fp_curve(spark, scenarios.bench(spark, sf_dir, share=0.5))
    known = theory.curve(spark).select(F.col("flip").alias("at"), "normal")
    return rounded(found.join(F.broadcast(known), F.round("flip", 4) == F.round("at", 4)).select("flip", "dummies", "measured", "normal", (F.col("normal") - F.col("measured")).alias("error")))


@query()
def sweep_flip(spark, sf_dir):
    """The same on the larger pair, beside all three predictions."""
    found = scenarios.dummy_fp_curve(spark, scenarios.bench(spark, sf_dir))
    known = theory.curve(spark).withColumnRenamed("flip", "at")
    return rounded(found.join(F.broadcast(known), F.round("flip", 4) == F.round("at", 4)).select("flip", "dummies", "measured", "exact", "normal", "flip_noise"))


# Cost per group.


def spending() -> list[Run]:
    return [Run("b1"), *(Run(n, e) for n in ("b2", "b", "cost") for e in (0.1, 10.0))]


_SPENT = """SELECT scenario, eps, group_id, sum(na * nb)::BIGINT AS real, sum((na + ma) * (nb + mb) - na * nb)::BIGINT AS fake FROM (
    SELECT scenario, runs.eps, table_no, label, s.group_id, coalesce(sum(s.n) FILTER (WHERE s.party = 'A'), 0) AS na, coalesce(sum(s.n) FILTER (WHERE s.party = 'B'), 0) AS nb, coalesce(sum(m) FILTER (WHERE s.party = 'A'), 0) AS ma, coalesce(sum(m) FILTER (WHERE s.party = 'B'), 0) AS mb
    FROM runs CROSS JOIN stats s LEFT JOIN (SELECT run, party, table_no, label, group_id, m FROM rcnt) USING (run, party, table_no, label, group_id) GROUP BY ALL) GROUP BY ALL"""
_SPENT = f"SELECT *, real + fake AS pairs, {rate('fake', 'real')} AS overhead FROM ({_SPENT})"


def _costs(spark, sf_dir, flavour: str) -> DataFrame:
    """Pairs per group of each run from bin sizes; no pair is made."""
    b = scenarios.bench(spark, sf_dir, flavour, keep=True)
    runs = spending()
    knobs = scenarios.knobs_of_runs(spark, b, runs)
    counts = noise.dummy_counts(b.stats, knobs).select("run", *noise.KEYS, "m")
    named = spark.createDataFrame([(i, r.scenario, float(r.eps)) for i, r in enumerate(runs)], "run int, scenario string, eps double")
    every = b.stats.crossJoin(F.broadcast(named)).join(counts, ["run", *noise.KEYS], "left").withColumn("m", F.coalesce("m", F.lit(0)))  # rows of bins and groups times seven runs
    return rounded(measures.cost(every, ["scenario", "eps"]))


@query(runs_sql(_SPENT, spending()))
def costs_clean(spark, sf_dir):
    return _costs(spark, sf_dir, "clean")


@query(runs_sql(_SPENT, spending(), recs=_DIRTY))
def costs_dirty(spark, sf_dir):
    return _costs(spark, sf_dir, "dirty")


@query(runs_sql(_SPENT, spending(), enc=_CENSUS))
def costs_census(spark, sf_dir):
    return _costs(spark, sf_dir, "census")


# Published settings: 30 hash functions, two encodings, labels of 30 bits.

PUBLISHED = replace(DEFAULT, k_hash=30, label_bits=30)
_PUBLISHED = {
    "enc": f"SELECT *, ({ONES})::INTEGER AS n_ones FROM ({encoded('recs', k=30, rounds=2)})",
    "lab": "SELECT *, " + ", ".join(f"{label(t, PUBLISHED)}::BIGINT AS l{t}" for t in range(5)) + " FROM enc",
}
_PUBLISHED_RUNS = [Run("b1"), Run("b2", 0.1), Run("b2", 1.0), Run("b2", 10.0)]


@query(runs_sql(SUMMARY, _PUBLISHED_RUNS, **_PUBLISHED))
def published_settings(spark, sf_dir):
    counts = scenarios.grid(spark, sf_dir, _PUBLISHED_RUNS, settings=PUBLISHED, rounds=2)
    return rounded(scenarios.summaries(counts).select(*SHOWN))


@query(sql("SELECT party, group_id, count(*) AS n FROM recs GROUP BY ALL", "recs", recs=_HALF))
def party_split_half(spark, sf_dir):
    """The smaller pair of parties."""
    return people.parties(spark, sf_dir, share=0.5).groupBy("party", "group_id").agg(F.count("*").alias("n"))


# Other ways of blocking, and clear text in the same bins.

_MERGED = "SELECT blk.* REPLACE (bin AS label) FROM blk JOIN (SELECT table_no, label, floor(coalesce(sum(n) OVER (PARTITION BY table_no ORDER BY label ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) / 20)::BIGINT AS bin FROM (SELECT table_no, label, count(*) AS n FROM blk GROUP BY ALL)) USING (table_no, label)"
_MET = f"""SELECT group_id, truth, CASE WHEN ones_a + ones_b = 0 THEN 0.0 ELSE 2.0 * common / (ones_a + ones_b) END AS sim FROM (SELECT DISTINCT a.rec_id AS id_a, b.rec_id AS id_b, a.group_id, a.entity_id = b.entity_id AS truth, {COMMON} AS common, a.n_ones AS ones_a, b.n_ones AS ones_b
    FROM merged a JOIN merged b ON a.party = 'A' AND b.party = 'B' AND a.table_no = b.table_no AND a.label = b.label AND a.group_id = b.group_id)"""


@query(sql(f"{RATES} FROM c", "blk", "truth", merged=_MERGED, p=_MET, c=_conf("p")))
def scenario_k_anonymous_rates(spark, sf_dir):
    """Linkage in bins merged to 20 records: a pair that meets in several tables counts once."""
    b = scenarios.bench(spark, sf_dir, keep=True)
    rows = written(block.merged(b.blocked, 20), "merged")
    # A merged bin is the label of each table, so that the first-table rule holds.
    wide = rows.groupBy("rec_id").agg(*(F.max(F.when(F.col("table_no") == t, F.col("label"))).alias(f"l{t}") for t in range(DEFAULT.label_tables)))
    rows = rows.drop(*(f"l{t}" for t in range(DEFAULT.label_tables))).join(wide, "rec_id")
    return rounded(measures.rates(measures.confusion(classify.threshold(pairs.candidates(*pairs.split(rows))), b.truth)))


@query()
def scenario_k_padded(spark, sf_dir):
    """Linkage in bins that are padded with dummies to 5 records."""
    b = scenarios.bench(spark, sf_dir, keep=True)
    rows = noise.padded(b.blocked, 5, DEFAULT.flip)
    return rounded(measures.rates(measures.confusion(classify.threshold(pairs.candidates(*pairs.split(rows))), b.truth)))


@query(sql("SELECT party, table_no, label, greatest(n, 5)::BIGINT AS size, greatest(0, 5 - n)::BIGINT AS dummies FROM (SELECT party, table_no, label, count(*) AS n FROM blk GROUP BY ALL)", "blk"))
def k_padded_bins(spark, sf_dir):
    rows = noise.padded(scenarios.bench(spark, sf_dir).blocked, 5, DEFAULT.flip)
    return rows.groupBy("party", *block.BIN).agg(F.count("*").alias("size"), F.count_if("is_dummy").alias("dummies"))


_CLEAR = f"""SELECT p.group_id, p.truth, 2.0 * len(list_intersect(a.t, b.t)) / (len(a.t) + len(b.t)) AS sim FROM pairs p
    JOIN (SELECT rec_id, {TOKENS} AS t FROM recs) a ON p.id_a = a.rec_id JOIN (SELECT rec_id, {TOKENS} AS t FROM recs) b ON p.id_b = b.rec_id"""


@query(sql(f"{RATES} FROM c", "pairs", "truth", p=_CLEAR, c=_conf("p")))
def scenario_unencoded(spark, sf_dir):
    """Clear-text tokens compared in the same bins: the price of encoding."""
    rows = people.parties(spark, sf_dir)
    coded = encode.bloom(rows, encode.voter_tokens()).withColumn("tokens", encode.voter_tokens())
    blocked = block.bit_labels(coded)
    found = pairs.candidates(*pairs.split(blocked)).withColumn("sim", F.col("plain"))
    return rounded(measures.rates(measures.confusion(classify.threshold(found), measures.truth_pairs(*pairs.split(rows)))))


_NEAR_EARLIER = " OR ".join(f"(a.table_no > {t} AND bit_count(xor(a.l{t}, b.l{t})) <= 1)" for t in range(DEFAULT.label_tables))
_NEAR = f"""SELECT a.group_id, a.entity_id = b.entity_id AS truth, CASE WHEN a.n_ones + b.n_ones = 0 THEN 0.0 ELSE 2.0 * {COMMON} / (a.n_ones + b.n_ones) END AS sim FROM blk a JOIN blk b
    ON a.party = 'A' AND b.party = 'B' AND a.table_no = b.table_no AND bit_count(xor(a.label, b.label)) <= 1 AND a.group_id = b.group_id WHERE NOT ({_NEAR_EARLIER})"""


@query(sql(f"{RATES} FROM c", "blk", "truth", p=_NEAR, c=_conf("p")))
def scenario_near_labels(spark, sf_dir):
    """Linkage where bins whose labels differ in one bit are compared too."""
    b = scenarios.bench(spark, sf_dir, keep=True)
    found = pairs.near_candidates(*pairs.split(b.blocked), block.near_labels(b.stats, DEFAULT.label_bits))
    return rounded(measures.rates(measures.confusion(classify.threshold(found), b.truth)))


# Privacy, bias, scale, documents.

_GEOMETRIC = "floor(ln({}) / -1.0)::BIGINT - floor(ln({}) / -1.0)::BIGINT".format(u("ratio", "size", "id", seed=1), u("ratio", "size", "id", seed=2))


@query(f"SELECT value, own, neighbour, round(own / nullif(neighbour, 0)::DOUBLE, 6) AS ratio, round(exp(1.0::DOUBLE), 6) AS bound FROM (SELECT value, count(*) FILTER (WHERE size = 20) AS own, count(*) FILTER (WHERE size = 19) AS neighbour FROM (SELECT size, size + {_GEOMETRIC} AS value FROM (VALUES (20), (19)) t(size), (SELECT c_custkey AS id FROM customer)) GROUP BY value)")
def dp_ratio(spark, sf_dir):
    """Noisy sizes of two neighbouring bins over a draw for every customer: how often each value comes, and the ratio."""
    return rounded(noise.empirical_ratio(spark, 20, 1.0, table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"))))


@query()
def bias_census(spark, sf_dir):
    """Noise without groups and logistic on census-like records: rates, minority share and overlap of scores per group."""
    b = scenarios.bench(spark, sf_dir, "census", keep=True, attributes=True)
    counts = scenarios.grid(spark, sf_dir, [Run("b3", 1.0)], "census", classifiers=("logistic",), b=b)
    own = written(scenarios.original_pairs(b), "pairs")
    scored = scenarios.learner(b, own, "logistic")(scenarios.half(own).where("half")).withColumn("sim", F.col("score")).withColumn("fake", F.lit(False))
    overlap = measures.overlap_area(measures.histogram(scored))
    sizes = scenarios.group_sizes(b).select("group_id", (F.col("na") + F.col("nb")).alias("rows"))
    share = sizes.crossJoin(F.broadcast(sizes.agg(F.sum("rows").alias("all")))).select("group_id", (F.col("rows") / F.col("all")).alias("share"))
    return rounded(measures.rates(counts.select("group_id", "tp", "fp", "tn", "fn")).join(overlap, "group_id").join(share, "group_id"))


@query()
def scale_out(spark, sf_dir):
    """Comparisons as records grow by 1, 2 and 4: with fixed labels, and with a label bit more for each doubling."""
    out = []
    for times in (1, 2, 4):
        rows = people.parties(spark, sf_dir, copies=times)
        for bits_ in sorted({DEFAULT.label_bits, DEFAULT.label_bits + times.bit_length() - 1}):
            s = replace(DEFAULT, label_bits=bits_)
            stats = block.bin_stats(block.bit_labels(encode.encoded(rows, s), s))
            per = stats.agg((F.sum("n") / s.label_tables).cast("long").alias("records")).crossJoin(F.broadcast(block.comparisons(stats)))
            out.append(per.select(F.lit(times).alias("times"), F.lit(bits_).alias("label_bits"), "records", F.col("pairs").alias("comparisons"), (F.col("pairs") / F.col("records")).alias("per_record")))
    return rounded(reduce(DataFrame.unionByName, out))


_SHINGLES = "list_slice(list_sort(list_distinct(list_transform(range(1, greatest(1, len(ws) - 4) + 1), lambda i: md5(array_to_string(ws[i:i + 4], ' '))))), 1, 16)"
_DOCS = f"""SELECT *, {_SHINGLES} AS tokens FROM (SELECT CASE WHEN regexp_extract(source, '(\\d+)$', 1)::INTEGER % 2 = 0 THEN 'A' ELSE 'B' END AS party, 'doc-' || doc_id::VARCHAR AS rec_id, doc_id AS entity_id, md5(text) AS truth,
    CASE WHEN lang = 'en' THEN 'en' ELSE 'other' END AS group_id, string_split_regex(text, '[ \\n]+') AS ws FROM documents WHERE text IS NOT NULL)"""
_DOC_PAIRS = f"""SELECT group_id, n, same, 2.0 * common / (ones_a + ones_b) > 0.8 AS linked FROM (SELECT a.group_id, a.copies * b.copies AS n, a.truth = b.truth AS same, {COMMON} AS common, a.n_ones AS ones_a, b.n_ones AS ones_b
    FROM kinds a JOIN kinds b ON a.party = 'A' AND b.party = 'B' AND a.table_no = b.table_no AND a.label = b.label AND a.group_id = b.group_id WHERE NOT ({EARLIER}))"""
_KINDS = "SELECT party, group_id, table_no, label, l0, l1, l2, l3, l4, w0, w1, w2, w3, w4, n_ones, docs.truth, count(*) AS copies FROM blk JOIN (SELECT rec_id, truth FROM recs) docs USING (rec_id) GROUP BY ALL"


@query(sql("SELECT group_id, sum(n)::BIGINT AS pairs, coalesce(sum(n) FILTER (WHERE linked), 0)::BIGINT AS links, coalesce(sum(n) FILTER (WHERE same), 0)::BIGINT AS true_pairs, coalesce(sum(n) FILTER (WHERE linked AND same), 0)::BIGINT AS true_links FROM d GROUP BY group_id", "blk", recs=_DOCS, enc=f"SELECT *, ({ONES})::INTEGER AS n_ones FROM ({encoded('recs', 'tokens')})", kinds=_KINDS, d=_DOC_PAIRS))
def doc_copies(spark, sf_dir):
    """Whole texts as records of two parties: compared, linked and true pairs. Equal texts of a party are one weighted record."""
    docs = people.documents_as_records(spark, sf_dir)
    coded = encode.bloom(docs, F.col("tokens")).drop("tokens")
    kinds = coded.groupBy("party", "group_id", "truth", *[f"w{i}" for i in range(5)], "n_ones").agg(F.count("*").alias("copies"), F.min("rec_id").alias("rec_id"))
    blocked = block.bit_labels(kinds.withColumn("entity_id", F.xxhash64("truth")))
    # The 64-bit hash of the text's digest stands for the entity.
    many = blocked.where("table_no = 0").select("rec_id", "copies")
    found = classify.threshold(pairs.candidates(*pairs.split(blocked)))
    weighed = found.join(many.toDF("id_a", "ca"), "id_a").join(many.toDF("id_b", "cb"), "id_b").withColumn("n", F.col("ca") * F.col("cb"))
    total = lambda c: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0)).cast("long")
    return weighed.groupBy("group_id").agg(F.sum("n").cast("long").alias("pairs"), total(F.col("pred")).alias("links"), total(F.col("truth")).alias("true_pairs"), total(F.col("pred") & F.col("truth")).alias("true_links"))
