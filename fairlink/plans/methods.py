"""Queries of the method itself: people, encoding, blocking, noise, linkage, measures, theory, tuners, scenarios."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fairlink.functions import bits, rng, theory, tokens
from fairlink.operators import allocate, allpairs, block, classify, corrupt, encode, measures, noise, pairs
from fairlink.plans import scenarios
from fairlink.plans.oracle import CENSUS, COMMON, EARLIER, ONES, RATES, SEED, STEPS, TOKENS, _conf, _pairs, encoded, expected_fakes, false_match, grams, group_rate, noise_sql, rate, runs_sql, sql, u
from fairlink.plans.registry import query, r6, rounded
from fairlink.settings import DEFAULT
from fairlink.sources import people
from fairlink.sources.steps import written
from fairlink.sources.tables import table

ATTRIBUTES = "entity_id, given, surname, suburb, postcode, gender, age, array_to_string(industries, ',') AS industries, full_time, area, mesh"


def _groups(spark: SparkSession) -> DataFrame:
    return noise.equal_knobs(spark, ["m", "w"])


def _flat(df: DataFrame) -> DataFrame:
    return df.withColumn("industries", F.array_join("industries", ","))


# People and workloads.


@query(sql(f"SELECT {ATTRIBUTES}, lot FROM people", "people"))
def person_view(spark, sf_dir):
    return _flat(people.persons(spark, sf_dir))


@query(sql(f"SELECT party, rec_id, {ATTRIBUTES}, group_id FROM recs", "recs"))
def party_split(spark, sf_dir):
    return _flat(people.parties(spark, sf_dir))


@query(sql("SELECT word, n, place FROM lex", "lex"))
def lexicon_words(spark, sf_dir):
    return people.lexicon(spark, sf_dir)


@query(sql("SELECT gender || '/' || CASE WHEN age <= 45 THEN 'young' ELSE 'old' END AS group_id, party, count(*) AS n FROM recs GROUP BY ALL", "recs"))
def groups_product(spark, sf_dir):
    return people.parties(spark, sf_dir, features=("gender", "age_band")).groupBy("group_id", "party").agg(F.count("*").alias("n"))


def _edit_sql(column: str, index: int) -> str:
    place = f"(floor({u('place', 'entity_id')} * length({column})) + 1)::INTEGER"
    letter = f"substr('{corrupt.LETTERS}', (floor({u('letter', 'entity_id')} * 26) + 1)::INTEGER, 1)"
    op = f"floor({u('op', 'entity_id')} * 6)::INTEGER"
    head, here, tail = f"substr({column}, 1, {place} - 1)", f"substr({column}, {place}, 1)", f"substr({column}, {place} + 1)"

    def swap(pairs_: dict[str, str]) -> str:
        return "CASE " + " ".join(f"WHEN contains({column}, '{a}') THEN replace({column}, '{a}', '{b}')" for a, b in pairs_.items()) + f" ELSE {column} END"

    done = (
        f"CASE {op} WHEN 0 THEN {head} || {letter} || {here} || {tail} WHEN 1 THEN {head} || {tail} WHEN 2 THEN {head} || {letter} || {tail} "
        f"WHEN 3 THEN {head} || substr({column}, {place} + 1, 1) || {here} || substr({column}, {place} + 2) WHEN 4 THEN {swap(corrupt.LOOKS)} ELSE {swap(corrupt.SOUNDS)} END"
    )
    hit = f"{u('edit', 'entity_id')} < 0.5 AND floor({u('column', 'entity_id')} * 4) = {index}"
    return f"CASE WHEN coalesce({column}, '') <> '' AND {hit} THEN {done} ELSE {column} END AS {column}"


@query(sql("SELECT entity_id, " + ", ".join(_edit_sql(c, i) for i, c in enumerate(("given", "surname", "suburb", "postcode"))) + " FROM people WHERE lot <> 1", "people"))
def corrupt_edits(spark, sf_dir):
    return people.parties(spark, sf_dir, "dirty").where("party = 'B'").select("entity_id", "given", "surname", "suburb", "postcode")


def _fresh_sql(c: str) -> str:
    code = f"md5('{SEED}|new-{c}|' || entity_id::VARCHAR)"
    return f"CASE WHEN {u('replace', 'entity_id')} < CASE gender WHEN 'm' THEN 0.1 ELSE 0.3 END THEN substr(translate({code}, '0123456789', 'ghijklmnop'), 1, 7) ELSE {c} END AS {c}"


@query(sql("SELECT entity_id, gender, " + ", ".join(map(_fresh_sql, ("surname", "suburb", "postcode"))) + " FROM people WHERE lot <> 1", "people"))
def corrupt_replace(spark, sf_dir):
    return people.parties(spark, sf_dir, "biased").where("party = 'B'").select("entity_id", "gender", "surname", "suburb", "postcode")


@query(sql(f"SELECT party, rec_id, array_to_string(list_sort({CENSUS}), ' ') AS tokens FROM recs", "recs"))
def census_view(spark, sf_dir):
    return people.parties(spark, sf_dir, "census").select("party", "rec_id", F.array_join(F.array_sort(encode.census_tokens()), " ").alias("tokens"))


# Encoding.


@query(sql(f"SELECT party, rec_id, array_to_string(list_sort({TOKENS}), ' ') AS tokens FROM recs", "recs"))
def qgram_tokens(spark, sf_dir):
    return people.parties(spark, sf_dir).select("party", "rec_id", F.array_join(F.array_sort(encode.voter_tokens()), " ").alias("tokens"))


@query("SELECT c_custkey, array_to_string(list_transform(range(floor(c_acctbal / 500)::BIGINT - 2, floor(c_acctbal / 500)::BIGINT + 3), lambda b: 'n:' || b::VARCHAR), ' ') AS tokens FROM customer")
def near_tokens(spark, sf_dir):
    return table(spark, sf_dir, "customer").select("c_custkey", F.array_join(tokens.near(F.col("c_acctbal"), "n:", 500, 2), " ").alias("tokens"))


@query(sql("SELECT party, rec_id, entity_id, group_id, w0, w1, w2, w3, w4, n_ones FROM enc", "enc"))
def bloom_words(spark, sf_dir):
    return encode.encoded(people.parties(spark, sf_dir))


_SURNAME = f"SELECT party, rec_id, w0, w1, w2, w3, w4 FROM ({encoded('recs', grams('surname', 's:'), 30)})"


@query(sql(_SURNAME, "recs"))
def bloom_attribute(spark, sf_dir):
    return encode.bloom_attributes(people.parties(spark, sf_dir)).select("party", "rec_id", *[F.col(f"t1w{i}").alias(f"w{i}") for i in range(5)])


@query(sql("SELECT party, count(*) AS n, round(avg(n_ones / 300.0), 6) AS fill, round(stddev_pop(n_ones / 300.0), 6) AS fill_sd FROM enc GROUP BY party", "enc"))
def fill_stats(spark, sf_dir):
    return rounded(encode.fill_stats(encode.encoded(people.parties(spark, sf_dir))))


@query(sql(f"SELECT round(m, 6) AS mean_tokens, floor(300 * ln(2) / m + 0.5)::INTEGER AS k FROM (SELECT avg(len({TOKENS})) AS m FROM recs)", "recs"))
def auto_k(spark, sf_dir):
    mean = encode.mean_tokens(people.parties(spark, sf_dir), encode.voter_tokens())
    return mean.select(r6("mean_tokens"), F.floor(300 * F.ln(F.lit(2.0)) / F.col("mean_tokens") + 0.5).cast("int").alias("k"))


@query(
    "SELECT vec_id, "
    + ", ".join(f"(SELECT coalesce(sum(CASE WHEN embedding[{60 * w} + i + 1] > 0 THEN (1::BIGINT << i::INTEGER) ELSE 0 END), 0)::BIGINT FROM range({min(60, 64 - 60 * w)}) r(i)) AS b{w}" for w in (0, 1))
    + " FROM embeddings"
)
def sign_bits(spark, sf_dir):
    a, b = encode.sign_bits(F.col("embedding"))
    return table(spark, sf_dir, "embeddings").select("vec_id", a.alias("b0"), b.alias("b1"))


# Blocking.


def _blocked(spark, sf_dir, flavour="clean"):
    return scenarios.bench(spark, sf_dir, flavour).blocked


@query(sql("SELECT party, rec_id, table_no, label FROM blk", "blk"))
def bit_labels(spark, sf_dir):
    return _blocked(spark, sf_dir).select("party", "rec_id", "table_no", "label")


@query(sql("SELECT party, 0 AS table_no, surname || '|' || suburb AS label, group_id, count(*) AS n FROM recs GROUP BY ALL", "recs"))
def key_blocks(spark, sf_dir):
    return block.bin_stats(block.by_key(people.parties(spark, sf_dir), ["surname", "suburb"]))


@query(sql("SELECT party, 0 AS table_no, substr(surname, 1, 3) AS label, group_id, count(*) AS n FROM recs GROUP BY ALL", "recs"))
def prefix_blocks(spark, sf_dir):
    rows = people.parties(spark, sf_dir).withColumn("key", F.substring("surname", 1, 3))
    return block.bin_stats(block.by_key(rows, ["key"]))


@query(sql("SELECT * FROM stats", "stats"))
def bin_stats(spark, sf_dir):
    return scenarios.bench(spark, sf_dir).stats


@query(sql("SELECT DISTINCT a.table_no, a.label AS label_a, b.label AS label_b FROM (SELECT DISTINCT table_no, label FROM stats) a JOIN (SELECT DISTINCT table_no, label FROM stats) b ON a.table_no = b.table_no AND bit_count(xor(a.label, b.label)) <= 1", "stats"))
def near_labels(spark, sf_dir):
    return block.near_labels(scenarios.bench(spark, sf_dir).stats, DEFAULT.label_bits)


@query(sql("SELECT party, table_no, label, n, floor(coalesce(sum(n) OVER (PARTITION BY party, table_no ORDER BY label ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) / 10)::BIGINT AS bin FROM (SELECT party, table_no, label, count(*) AS n FROM blk GROUP BY ALL)", "blk"))
def k_anonymous_bins(spark, sf_dir):
    return block.k_anonymous(_blocked(spark, sf_dir), 10)


_PAIR_COUNT = "SELECT coalesce(sum(a * b), 0)::BIGINT AS pairs FROM (SELECT table_no, label, sum(n) FILTER (WHERE party = 'A') AS a, sum(n) FILTER (WHERE party = 'B') AS b FROM stats GROUP BY ALL)"
_REACHED = "SELECT count(*) AS found FROM (SELECT DISTINCT a.rec_id FROM blk a JOIN blk b ON a.party = 'A' AND b.party = 'B' AND a.entity_id = b.entity_id AND a.table_no = b.table_no AND a.label = b.label)"


@query(sql(f"SELECT round(1 - pairs / ((SELECT count(*) FROM recs WHERE party = 'A') * (SELECT count(*) FROM recs WHERE party = 'B'))::DOUBLE, 6) AS reduction, round(found / (SELECT count(*) FROM truth)::DOUBLE, 6) AS completeness FROM ({_PAIR_COUNT}), ({_REACHED})", "stats", "truth", "blk"))
def blocking_quality(spark, sf_dir):
    b = scenarios.bench(spark, sf_dir)
    sides = b.blocked.where("table_no = 0").agg(F.count_if(F.col("party") == "A").alias("na"), F.count_if(F.col("party") == "B").alias("nb"))
    found = scenarios.plain_pairs(b).where("truth").agg(F.count("*").alias("found"))
    every = b.truth.agg(F.count("*").alias("truth"))
    return rounded(block.quality(b.stats.transform(lambda d: d), found, every.crossJoin(sides), F.col("na"), F.col("nb")))


# Noise.


@query(sql(f"SELECT party, table_no, label, group_id, round(-0.5 * sign(d - 0.5) * ln(1 - 2 * abs(d - 0.5)), 6) AS x FROM (SELECT *, {u('noise', 'party', 'table_no', 'label', 'group_id')} AS d FROM stats)", "stats"))
def keyed_laplace(spark, sf_dir):
    return scenarios.bench(spark, sf_dir).stats.select(*noise.KEYS, r6(rng.laplace(rng.uniform(7, "noise", *noise.KEYS), 0.5), "x"))


_KEY4 = ("party", "table_no", "label", "group_id")


@query(sql(f"SELECT party, table_no, label, group_id, n, least(n, greatest(0, floor(ln({u('noise', *_KEY4)}) / -2.0)::BIGINT - floor(ln({u('noise2', *_KEY4)}) / -2.0)::BIGINT))::BIGINT AS m FROM stats", "stats"))
def geometric_counts(spark, sf_dir):
    return noise.dummy_counts(scenarios.bench(spark, sf_dir).stats, _groups(spark), mechanism="geometric").select(*noise.KEYS, "n", "m")


@query(sql("SELECT party, table_no, label, group_id, n, m FROM counts", "counts"))
def dummy_counts(spark, sf_dir):
    return noise.dummy_counts(scenarios.bench(spark, sf_dir).stats, _groups(spark)).select(*noise.KEYS, "n", "m")


@query(sql("SELECT party, table_no, label, group_id, n, m FROM counts", "stats", counts=noise_sql("0.1", cap="greatest(0, m)").replace("STATS", "stats")))
def dummy_counts_uncapped(spark, sf_dir):
    knobs = noise.equal_knobs(spark, ["m", "w"]).withColumn("eps", F.lit(0.1))
    return noise.dummy_counts(scenarios.bench(spark, sf_dir).stats, knobs, cap=False).select(*noise.KEYS, "n", "m")


@query(sql("SELECT 'ceil' AS rounding, sum(m)::BIGINT AS dummies FROM up UNION ALL SELECT 'floor', sum(m)::BIGINT FROM down", "stats", up=noise_sql(rounding="ceil(x)").replace("STATS", "stats"), down=noise_sql(rounding="floor(x)").replace("STATS", "stats")))
def dummy_counts_rounding(spark, sf_dir):
    stats, knobs = scenarios.bench(spark, sf_dir).stats, _groups(spark)
    rows = [noise.dummy_counts(stats, knobs, rounding=r).agg(F.sum("m").alias("dummies")).select(F.lit(r).alias("rounding"), "dummies") for r in ("ceil", "floor")]
    return reduce(DataFrame.unionByName, rows)


_RECORD = noise_sql("1.0", key="party, table_no, label").replace("STATS", "(SELECT party, table_no, label, sum(n)::BIGINT AS n FROM stats GROUP BY ALL)")


@query(sql("SELECT party, table_no, label, n, m FROM counts", "stats", counts=_RECORD))
def record_dp_counts(spark, sf_dir):
    return noise.record_dp_counts(_blocked(spark, sf_dir), 1.0)


@query(sql("SELECT rec_id, table_no FROM chosen", "chosen"))
def dummy_pick(spark, sf_dir):
    b = scenarios.bench(spark, sf_dir)
    return noise.picked(b.blocked, noise.dummy_counts(b.stats, _groups(spark))).select("rec_id", "table_no")


def _dummies(spark, sf_dir):
    b = scenarios.bench(spark, sf_dir)
    chosen = noise.picked(b.blocked, noise.dummy_counts(b.stats, _groups(spark))).withColumn("flip", F.lit(DEFAULT.flip))
    return noise.dummies(chosen)


@query(sql("SELECT rec_id, parent_id, party, table_no, label, group_id, w0, w1, w2, w3, w4, n_ones FROM dums", "dums"))
def dummy_rows(spark, sf_dir):
    return _dummies(spark, sf_dir).select("rec_id", "parent_id", "party", "table_no", "label", "group_id", *bits.names(), "n_ones")


def _noisy(spark, sf_dir):
    return noise.feature_dp(_blocked(spark, sf_dir), _groups(spark))


@query(sql("SELECT party, table_no, label, group_id, count(*) AS n, count(*) FILTER (WHERE is_dummy) AS n_dummy FROM noisy GROUP BY ALL", "noisy"))
def noisy_bins(spark, sf_dir):
    return _noisy(spark, sf_dir).groupBy(*noise.KEYS).agg(F.count("*").alias("n"), F.count_if("is_dummy").alias("n_dummy"))


@query(sql(f"SELECT md5('7|opaque|' || rec_id || '|' || is_dummy::VARCHAR) AS rec_id, party, table_no, label, group_id, n_ones FROM noisy", "noisy"))
def opaque_rows(spark, sf_dir):
    return noise.opaque(_noisy(spark, sf_dir)).select("rec_id", "party", "table_no", "label", "group_id", "n_ones")


# Linkage.


@query(sql("SELECT table_no, label, id_a, id_b, group_id, truth FROM pairs", "pairs"))
def candidates_plain(spark, sf_dir):
    return scenarios.plain_pairs(scenarios.bench(spark, sf_dir)).select("table_no", "label", "id_a", "id_b", "group_id", "truth")


def _noisy_pairs(spark, sf_dir, **options):
    return pairs.candidates(*pairs.split(_noisy(spark, sf_dir)), **options)


@query(sql("SELECT table_no, label, id_a, id_b, group_id, fake, truth FROM npairs", "npairs"))
def candidates_noisy(spark, sf_dir):
    return _noisy_pairs(spark, sf_dir).select("table_no", "label", "id_a", "id_b", "group_id", "fake", "truth")


@query(sql("SELECT group_id, fake, count(*) AS n FROM npairs GROUP BY ALL", "noisy", npairs=_pairs("noisy", "")))
def candidates_all_groups(spark, sf_dir):
    return _noisy_pairs(spark, sf_dir, scope="all").groupBy("group_id", "fake").agg(F.count("*").alias("n"))


@query(sql("SELECT id_a, id_b, table_no, round(sim, 6) AS sim FROM npairs", "npairs"))
def dice_scores(spark, sf_dir):
    return _noisy_pairs(spark, sf_dir).select("id_a", "id_b", "table_no", r6("sim"))


@query(sql("SELECT id_a, id_b, round(common / (ones_a + ones_b - common)::DOUBLE, 6) AS jaccard, round(common / sqrt((ones_a * ones_b)::DOUBLE), 6) AS cosine, round(common / least(ones_a, ones_b)::DOUBLE, 6) AS overlap, ones_a + ones_b - 2 * common AS hamming FROM pairs", "pairs"))
def bit_similarities(spark, sf_dir):
    s = pairs.bit_similarities()
    return scenarios.plain_pairs(scenarios.bench(spark, sf_dir)).select("id_a", "id_b", *[r6(s[c], c) for c in ("jaccard", "cosine", "overlap")], s["hamming"].alias("hamming"))


_PLAIN = f"""SELECT a.rec_id AS id_a, b.rec_id AS id_b, round(2.0 * len(list_intersect(a.t, b.t)) / (len(a.t) + len(b.t)), 6) AS dice, round(1 - levenshtein(a.surname, b.surname) / greatest(length(a.surname), length(b.surname))::DOUBLE, 6) AS surname_sim
FROM (SELECT *, {TOKENS} AS t FROM recs WHERE party = 'A') a JOIN (SELECT *, {TOKENS} AS t FROM recs WHERE party = 'B') b ON a.suburb = b.suburb AND a.group_id = b.group_id AND substr(a.given, 1, 1) = substr(b.given, 1, 1)"""


@query(sql(_PLAIN, "recs"))
def plain_scores(spark, sf_dir):
    """Clear-text similarities of pairs of one suburb, group and first letter: token sets, and surnames by edits."""
    rows = people.parties(spark, sf_dir).withColumn("t", encode.voter_tokens()).withColumn("first", F.substring("given", 1, 1))
    key = ["suburb", "group_id", "first"]
    left = rows.where("party = 'A'").select(*key, F.col("surname").alias("sa"), F.col("rec_id").alias("id_a"), F.col("t").alias("ta"))
    right = rows.where("party = 'B'").select(*key, F.col("surname").alias("sb"), F.col("rec_id").alias("id_b"), F.col("t").alias("tb"))
    return left.join(right, key).select("id_a", "id_b", r6(pairs.token_dice(F.col("ta"), F.col("tb")), "dice"), r6(pairs.edit_similarity(F.col("sa"), F.col("sb")), "surname_sim"))


@query(sql("SELECT id_a, id_b, round(sim, 6) AS sim FROM pairs WHERE sim > 0.8", "pairs"))
def threshold_links(spark, sf_dir):
    return classify.threshold(scenarios.plain_pairs(scenarios.bench(spark, sf_dir))).where("pred").select("id_a", "id_b", r6("sim"))


@query(sql("SELECT id_a, id_b FROM pairs WHERE sim > 0.8 QUALIFY row_number() OVER (PARTITION BY id_a ORDER BY sim DESC, id_b) = 1 AND row_number() OVER (PARTITION BY id_b ORDER BY sim DESC, id_a) = 1", "pairs"))
def mutual_best(spark, sf_dir):
    return classify.mutual_best(classify.threshold(scenarios.plain_pairs(scenarios.bench(spark, sf_dir))).where("pred")).select("id_a", "id_b")


def _learned(spark, sf_dir, kind):
    """Rates of a learned classifier on the test half of dirty records, from the similarities of attributes and of the record."""
    counts = scenarios.grid(spark, sf_dir, [scenarios.Run("b1")], "dirty", classifiers=(kind,))
    return rounded(measures.rates(counts.select("group_id", "tp", "fp", "tn", "fn")))


@query()
def logistic_links(spark, sf_dir):
    return _learned(spark, sf_dir, "logistic_plain")


@query()
def logistic_weighted(spark, sf_dir):
    return _learned(spark, sf_dir, "logistic")


@query()
def tree_links(spark, sf_dir):
    return _learned(spark, sf_dir, "tree")


@query()
def forest_links(spark, sf_dir):
    return _learned(spark, sf_dir, "forest")


@query()
def svm_links(spark, sf_dir):
    return _learned(spark, sf_dir, "svm")


_THREE = "SELECT *, gender AS group_id, party || '-' || entity_id::VARCHAR AS rec_id FROM (" + " UNION ALL ".join(f"SELECT *, '{p}' AS party FROM people WHERE lot <> {n}" for p, n in (("A", 2), ("B", 1), ("C", 0))) + ")"


@query(sql("SELECT parties, count(*) AS n FROM (" + " UNION ALL ".join(f"SELECT '{p}{q}' AS parties FROM blk a JOIN blk b ON a.party = '{p}' AND b.party = '{q}' AND a.table_no = b.table_no AND a.label = b.label AND a.group_id = b.group_id WHERE NOT ({EARLIER})" for p, q in ("AB", "AC", "BC")) + ") GROUP BY parties", "blk", recs=_THREE))
def three_parties(spark, sf_dir):
    blocked = block.bit_labels(encode.encoded(people.three_parties(spark, sf_dir)))
    return pairs.multi_party({p: blocked.where(F.col("party") == p) for p in "ABC"}).groupBy("parties").agg(F.count("*").alias("n"))


# Measures.


def _judged(spark, sf_dir):
    return classify.threshold(_noisy_pairs(spark, sf_dir))


def _confused(spark, sf_dir):
    b = scenarios.bench(spark, sf_dir)
    return measures.confusion(classify.threshold(pairs.candidates(*pairs.split(noise.feature_dp(b.blocked, _groups(spark))))), b.truth)


@query(sql("SELECT group_id, tp, fp, tn, fn FROM nconf", "nconf"))
def confusion_by_group(spark, sf_dir):
    return _confused(spark, sf_dir)


@query(sql(f"{RATES} FROM nconf", "nconf"))
def rates_by_group(spark, sf_dir):
    return rounded(measures.rates(_confused(spark, sf_dir)))


_LOSS = f"SELECT max(fp / greatest(1, fp + tn)::DOUBLE) - min(fp / greatest(1, fp + tn)::DOUBLE) AS a, max(fn / greatest(1, fn + tp)::DOUBLE) - min(fn / greatest(1, fn + tp)::DOUBLE) AS b FROM nconf"


@query(sql(f"SELECT round(a, 6) AS fpr_gap, round(b, 6) AS fnr_gap, round(greatest(a, b), 6) AS loss, round(1 - greatest(a, b), 6) AS fairness FROM ({_LOSS})", "nconf"))
def fairness_loss(spark, sf_dir):
    return rounded(measures.fairness(measures.rates(_confused(spark, sf_dir))))


@query(sql("SELECT round(max(r) - min(r), 6) AS parity_gap, round(max(t) - min(t), 6) AS opportunity_gap FROM (SELECT (tp + fp) / (tp + fp + tn + fn)::DOUBLE AS r, tp / greatest(1, tp + fn)::DOUBLE AS t FROM nconf)", "nconf"))
def parity_gaps(spark, sf_dir):
    return rounded(measures.parity(_confused(spark, sf_dir)))


@query(sql(_PAIR_COUNT, "stats"))
def comparisons_cost(spark, sf_dir):
    return block.comparisons(scenarios.bench(spark, sf_dir).stats)


_COST = """SELECT group_id, sum(na * nb)::BIGINT AS real, sum((na + ma) * (nb + mb) - na * nb)::BIGINT AS fake FROM (
    SELECT table_no, label, group_id, coalesce(sum(n) FILTER (WHERE party = 'A'), 0) AS na, coalesce(sum(n) FILTER (WHERE party = 'B'), 0) AS nb, coalesce(sum(m) FILTER (WHERE party = 'A'), 0) AS ma, coalesce(sum(m) FILTER (WHERE party = 'B'), 0) AS mb
    FROM counts GROUP BY ALL) GROUP BY group_id"""


@query(sql(f"SELECT *, real + fake AS pairs, {rate('fake', 'real')} AS overhead FROM ({_COST})", "counts"))
def fake_pair_cost(spark, sf_dir):
    return rounded(measures.cost(noise.dummy_counts(scenarios.bench(spark, sf_dir).stats, _groups(spark))))


@query(sql("SELECT party, group_id, sum(m)::BIGINT AS dummies, (sum(n + m) * 40)::BIGINT AS bytes FROM counts GROUP BY ALL", "counts"))
def communication_cost(spark, sf_dir):
    return measures.communication(noise.dummy_counts(scenarios.bench(spark, sf_dir).stats, _groups(spark)))


@query(sql("SELECT group_id, truth, least(19, floor(sim * 20))::INTEGER AS bucket, count(*) AS n FROM pairs GROUP BY ALL", "pairs"))
def sim_histogram(spark, sf_dir):
    return measures.histogram(scenarios.plain_pairs(scenarios.bench(spark, sf_dir)))


_HIST = "SELECT group_id, truth, least(19, floor(sim * 20))::INTEGER AS bucket, count(*) AS n FROM pairs GROUP BY ALL"


@query(sql(f"SELECT group_id, round(sum(least(m, o)), 6) AS overlap FROM (SELECT group_id, bucket, coalesce(sum(p) FILTER (WHERE truth), 0) AS m, coalesce(sum(p) FILTER (WHERE NOT truth), 0) AS o FROM (SELECT *, n / sum(n) OVER (PARTITION BY group_id, truth) AS p FROM ({_HIST})) GROUP BY ALL) GROUP BY group_id", "pairs"))
def sim_overlap(spark, sf_dir):
    return rounded(measures.overlap_area(measures.histogram(scenarios.plain_pairs(scenarios.bench(spark, sf_dir)))))


@query(sql("SELECT party, group_id, count(*) FILTER (WHERE same = 1) AS unique_bins, count(*) FILTER (WHERE n < 2) AS rare_bins, count(*) AS bins FROM (SELECT *, count(*) OVER (PARTITION BY party, table_no, n) AS same FROM stats) GROUP BY ALL", "stats"))
def exposure_rare_bins(spark, sf_dir):
    return measures.exposure(scenarios.bench(spark, sf_dir).stats)


@query(sql(f"SELECT count(*) AS dummies, round(avg((CASE WHEN 2.0 * {COMMON} / (a.n_ones + b.n_ones) > 0.8 THEN 1.0 ELSE 0.0 END)), 6) AS measured, 0.2::DOUBLE AS flip FROM dums a JOIN enc b ON a.parent_id = b.rec_id", "enc", "chosen", dums=STEPS["dums"].replace(f"< {DEFAULT.flip} THEN", "< 0.2 THEN")))
def dummy_fp_measured(spark, sf_dir):
    return rounded(scenarios.dummy_fp_curve(spark, scenarios.bench(spark, sf_dir)).where("round(flip, 4) = 0.2").select("dummies", "measured", "flip"))


# Theory. Flips are those that quantities of line items name, 1/50 to 1.

_NAMED = "(SELECT DISTINCT l_quantity AS f FROM lineitem WHERE l_quantity BETWEEN 0 AND 50) r"


def _named(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").where("l_quantity BETWEEN 0 AND 50").select((F.col("l_quantity") / 50).alias("flip")).distinct()


_EPS = (0.1, 0.2, 0.5, 1.0, 2.0, 5.0, 10.0)


@query("SELECT e::DOUBLE AS eps, round(1 / (2 * e), 6) AS mean, round(1 / (2 * e) * (1 - exp(-20 * e)), 6) AS capped20 FROM (SELECT DISTINCT l_quantity / 10 AS e FROM lineitem WHERE l_quantity > 0)")
def expected_dummies(spark, sf_dir):
    """Budgets are those that quantities of line items name, 0.1 to 5."""
    e = F.col("eps")
    return table(spark, sf_dir, "lineitem").where("l_quantity > 0").select((F.col("l_quantity") / 10).alias("eps")).distinct().select("eps", r6(1 / (2 * e), "mean"), r6(theory.capped_mean(F.lit(20.0), e), "capped20"))


@query("SELECT f / 50.0 AS flip, round(CASE WHEN f = 50 THEN 0 ELSE 1 / (1 + (f / 50.0) * 300 / (2 * (1 - f / 50.0) * 150)) END, 6) AS dice FROM " + _NAMED)
def dummy_dice_curve(spark, sf_dir):
    f = F.col("flip")
    return _named(spark, sf_dir).select("flip", r6(F.when(f == 1, 0.0).otherwise(1 / (1 + f * 300 / (2 * F.greatest(1 - f, F.lit(1e-12)) * 150))), "dice"))


_ERF = "(sign({x}) * (1 - (1 / (1 + 0.3275911 * abs({x}))) * (0.254829592 + (1 / (1 + 0.3275911 * abs({x}))) * (-0.284496736 + (1 / (1 + 0.3275911 * abs({x}))) * (1.421413741 + (1 / (1 + 0.3275911 * abs({x}))) * (-1.453152027 + (1 / (1 + 0.3275911 * abs({x}))) * 1.061405429)))) * exp(-({x}) * ({x}))))"
_FLIPS = "(SELECT f / 50.0::DOUBLE AS flip, CASE WHEN f < 50 THEN 300 * 0.8 * (f / 50.0::DOUBLE) / (2 * (1 - 0.8::DOUBLE) * (1 - f / 50.0::DOUBLE)) END AS cut, f FROM range(51) r(f))"
_NAMED_CUTS = _FLIPS.replace("range(51) r(f)", _NAMED)


@query(f"SELECT flip, round(CASE WHEN cut IS NULL THEN 0 ELSE coalesce((SELECT sum(exp(lgamma(301) - lgamma(k + 1) - lgamma(301 - k) + 300 * ln(0.5))) FROM range(301) q(k) WHERE k > cut), 0) END, 4) AS exact FROM {_NAMED_CUTS}")
def fp_prob_exact(spark, sf_dir):
    return theory.curve(spark, flips=_named(spark, sf_dir)).select("flip", F.round("exact", 4).alias("exact"))


@query(f"SELECT flip, round(CASE WHEN cut IS NULL THEN 0 ELSE 0.5 * (1 - {_ERF.format(x='((cut - 150) / sqrt(150.0::DOUBLE))')}) END, 6) AS normal FROM {_NAMED_CUTS}")
def fp_prob_normal(spark, sf_dir):
    return theory.curve(spark, flips=_named(spark, sf_dir)).select("flip", r6("normal"))


_M = "(2 * (1 - 0.8::DOUBLE) * 0.5 * (1 - flip) - 0.8 * flip)"
_V = f"(4 * (1 - 0.8::DOUBLE) * (1 - 0.8::DOUBLE) * 0.5 * (1 - flip) + 0.8::DOUBLE * 0.8 * flip - {_M} * {_M})"


@query(f"SELECT flip, round(CASE WHEN f = 0 THEN 1 ELSE 0.5 * (1 + {_ERF.format(x=f'(sqrt(300.0::DOUBLE) * {_M} / sqrt(2 * {_V}))')}) END, 6) AS flip_noise FROM {_NAMED_CUTS}")
def fp_prob_flip_noise(spark, sf_dir):
    return theory.curve(spark, flips=_named(spark, sf_dir)).select("flip", r6("flip_noise"))


_MEAN = "0.25 * (1 - exp(-n / 0.5))"


@query(sql(f"SELECT group_id, round(sum(na * mb + nb * ma + ma * mb), 4) AS fake, round((sum(na) + sum(nb)) / 4.0 + count(*) / 16.0, 4) AS collapsed FROM (SELECT table_no, label, group_id, coalesce(sum(n) FILTER (WHERE party = 'A'), 0) AS na, coalesce(sum(n) FILTER (WHERE party = 'B'), 0) AS nb, coalesce(sum({_MEAN}) FILTER (WHERE party = 'A'), 0) AS ma, coalesce(sum({_MEAN}) FILTER (WHERE party = 'B'), 0) AS mb FROM stats GROUP BY ALL) GROUP BY group_id", "stats"))
def fake_pairs_expected(spark, sf_dir):
    stats = scenarios.bench(spark, sf_dir).stats.withColumn("mean", theory.capped_mean(F.col("n"), F.lit(2.0)))
    side = lambda p, c: F.coalesce(F.sum(F.when(F.col("party") == p, F.col(c))), F.lit(0))
    wide = stats.groupBy(*block.BIN, "group_id").agg(side("A", "n").alias("na"), side("B", "n").alias("nb"), side("A", "mean").alias("ma"), side("B", "mean").alias("mb"))
    exact = F.sum(F.col("na") * F.col("mb") + F.col("nb") * F.col("ma") + F.col("ma") * F.col("mb"))
    return wide.groupBy("group_id").agg(F.round(exact, 4).alias("fake"), F.round((F.sum("na") + F.sum("nb")) / 4 + F.count("*") / 16, 4).alias("collapsed"))


_G = "SELECT c.group_id, fp, tn, na, nb, bins FROM conf c JOIN (SELECT group_id, coalesce(sum(n) FILTER (WHERE party = 'A'), 0) AS na, coalesce(sum(n) FILTER (WHERE party = 'B'), 0) AS nb FROM stats GROUP BY group_id) USING (group_id), (SELECT count(*) AS bins FROM (SELECT DISTINCT table_no, label FROM stats))"
_PFP = f"(0.5 * (1 - {_ERF.format(x='((300 * 0.8 * F / (2 * (1 - 0.8::DOUBLE) * (1 - F)) - 150) / sqrt(150.0::DOUBLE))')}))"


def _predicted(eps: str, flip: str) -> str:
    fake = f"((na + nb) / (2 * {eps}) + bins / (4 * {eps} * {eps}))"
    return f"(({_PFP.replace('F', flip)} * {fake} + fp) / ({fake} + fp + tn))"


@query(sql("SELECT group_id, e AS eps, round(" + _predicted("e", "0.4::DOUBLE") + ", 6) AS fpr FROM g, (VALUES " + ", ".join(f"({e}::DOUBLE)" for e in _EPS) + ") t(e)", "conf", "stats", g=_G))
def predicted_fpr(spark, sf_dir):
    g, e = _group_table(spark, sf_dir), F.col("eps")
    grid = g.crossJoin(F.broadcast(spark.createDataFrame([(x,) for x in _EPS], "eps double")))
    return grid.select("group_id", "eps", r6(_predicted_column(e, F.lit(0.4)), "fpr"))


def _group_table(spark, sf_dir):
    """One row per group: sizes, bins, original false positives and true negatives."""
    b = scenarios.bench(spark, sf_dir)
    counted = measures.confusion(classify.threshold(scenarios.plain_pairs(b)), b.truth)
    side = lambda p: F.coalesce(F.sum(F.when(F.col("party") == p, F.col("n"))), F.lit(0))
    sizes = b.stats.groupBy("group_id").agg(side("A").alias("na"), side("B").alias("nb"))
    bins = b.stats.select(*block.BIN).distinct().agg(F.count("*").alias("bins"))
    return counted.select("group_id", "fp", "tn").join(sizes, "group_id").crossJoin(F.broadcast(bins))


def _predicted_column(eps, flip):
    cut = 300 * 0.8 * flip / (2 * (1 - 0.8) * (1 - flip))
    p = 0.5 * (1 - theory.erf((cut - 150) / F.sqrt(F.lit(150.0))))
    fake = (F.col("na") + F.col("nb")) / (2 * eps) + F.col("bins") / (4 * eps * eps)
    return (p * fake + F.col("fp")) / (fake + F.col("fp") + F.col("tn"))


@query("SELECT o_custkey, round(1 / sum(1 / e), 6) AS harmonic, round(max(e), 6) AS parallel, round(sum(e), 6) AS sequential FROM (SELECT o_custkey, o_totalprice / 1000 AS e FROM orders WHERE o_totalprice > 0) GROUP BY o_custkey")
def budget_overall(spark, sf_dir):
    """Budgets of each customer, one an order by its price, put together in the three ways."""
    rows = table(spark, sf_dir, "orders").where("o_totalprice > 0").select("o_custkey", (F.col("o_totalprice") / 1000).alias("e"))
    return rows.groupBy("o_custkey").agg(r6(1 / F.sum(1 / F.col("e")), "harmonic"), r6(F.max("e"), "parallel"), r6(F.sum("e"), "sequential"))


# Tuners, as grids over a few rows and as the driver's solvers.


_TUNED = [scenarios.Run("a"), scenarios.Run("b"), scenarios.Run("cost")]


@query(runs_sql("SELECT group_id, kn.eps, kn.flip FROM kn JOIN runs USING (run) WHERE scenario = 'a'", _TUNED))
def method_a_flips(spark, sf_dir):
    """What Method A chooses at budget 1."""
    stats = scenarios.group_stats(scenarios.bench(spark, sf_dir, keep=True))
    return scenarios.knobs_of(spark, stats, allocate.flips(stats, theory.split_equal(1.0, len(stats))))


def _solved(spark, sf_dir, **options):
    stats = scenarios.group_stats(scenarios.bench(spark, sf_dir, keep=True))
    found = allocate.budgets(stats, 1.0, 0.4, **options)
    rows = [(s.group_id, round(float(e), 6), round(allocate.harmonic(found), 6), bool(found.at_border)) for s, e in zip(stats, found.eps, strict=True)]
    return spark.createDataFrame(rows, "group_id string, eps double, overall double, at_border boolean")


def _solved_sql(scenario: str) -> str:
    return runs_sql(f"SELECT group_id, round(kn.eps, 6) AS eps, 1.0::DOUBLE AS overall, 1 / kn.eps <= 0.05 * (1 + 1e-9) OR 1 - 1 / kn.eps <= 0.05 * (1 + 1e-9) AS at_border FROM kn JOIN runs USING (run) WHERE scenario = '{scenario}'", _TUNED)


@query(_solved_sql("b"))
def method_b_budgets(spark, sf_dir):
    return _solved(spark, sf_dir)


@query(_solved_sql("cost"))
def method_b_cost(spark, sf_dir):
    return _solved(spark, sf_dir, objective="cost")


def _weighted_sql() -> str:
    p, cost = false_match("0.4::DOUBLE"), lambda x: f"({expected_fakes('1', x)} + {expected_fakes('2', f'(1 - ({x}))')})"
    loss = f"greatest(abs({group_rate('1', 'x', p)} - {group_rate('2', '(1 - x)', p)}), fnr_gap)"
    best = f"SELECT g1, g2, x FROM two, (SELECT 0.05 + 0.9 * i / 200.0::DOUBLE AS x FROM range(201) r(i)) ORDER BY round({loss} + 0.5 * {cost('x')} / {cost('0.5')}, 12) LIMIT 1"
    return runs_sql(f"SELECT unnest([g1, g2]) AS group_id, round(unnest([1 / x, 1 / (1 - x)]), 6) AS eps, 1.0::DOUBLE AS overall, x <= 0.05 * (1 + 1e-9) OR 1 - x <= 0.05 * (1 + 1e-9) AS at_border FROM ({best})", _TUNED)


@query(_weighted_sql())
def method_b_weighted(spark, sf_dir):
    return _solved(spark, sf_dir, objective="weighted")


_STEPS = 100


@query(sql(f"SELECT i AS step, round((am + aw) * 0, 6) AS zero, round(am * xm + aw * xw + c * (xm * xm + xw * xw), 4) AS cost FROM (SELECT i, 0.05 + 0.9 * i / {_STEPS}.0 AS xm, 1 - (0.05 + 0.9 * i / {_STEPS}.0) AS xw, (SELECT (na + nb) / 2.0 FROM g WHERE group_id = 'm') AS am, (SELECT (na + nb) / 2.0 FROM g WHERE group_id = 'w') AS aw, (SELECT bins / 4.0 FROM g LIMIT 1) AS c FROM range({_STEPS + 1}) r(i))", "conf", "stats", g=_G))
def method_b_cost_grid(spark, sf_dir):
    g = _group_table(spark, sf_dir).agg(F.max(F.when(F.col("group_id") == "m", (F.col("na") + F.col("nb")) / 2)).alias("am"), F.max(F.when(F.col("group_id") == "w", (F.col("na") + F.col("nb")) / 2)).alias("aw"), (F.max("bins") / 4).alias("c"))
    xm = 0.05 + 0.9 * F.col("step") / _STEPS
    grid = spark.range(_STEPS + 1).withColumnRenamed("id", "step").crossJoin(F.broadcast(g))
    cost = F.col("am") * xm + F.col("aw") * (1 - xm) + F.col("c") * (xm * xm + (1 - xm) * (1 - xm))
    return grid.select("step", F.lit(0.0).alias("zero"), F.round(cost, 4).alias("cost"))


# Scenarios.


@query(sql(f"{RATES} FROM conf", "conf"))
def scenario_b1(spark, sf_dir):
    return rounded(measures.rates(scenarios.run(spark, sf_dir, "b1")))


@query(sql(f"{RATES} FROM nconf", "nconf"))
def scenario_b2(spark, sf_dir):
    return rounded(measures.rates(scenarios.run(spark, sf_dir, "b2")))


_B3_CHOSEN = f"SELECT blk.*, m FROM blk JOIN (SELECT party, table_no, label, m FROM counts WHERE m > 0) USING (party, table_no, label) QUALIFY row_number() OVER (PARTITION BY party, table_no, label ORDER BY md5('7|pick|' || rec_id || '|' || table_no::VARCHAR)) <= m"


@query(sql(f"{RATES} FROM nconf", "stats", "truth", "blk", **{"counts": _RECORD, "chosen": _B3_CHOSEN}, dums=STEPS["dums"], noisy=STEPS["noisy"], npairs="PAIRS(noisy)", nconf="CONF(npairs)"))
def scenario_b3(spark, sf_dir):
    return rounded(measures.rates(scenarios.run(spark, sf_dir, "b3")))


def _cells(scenario: str, **steps: str) -> str:
    return runs_sql(f"{RATES} FROM cells", [scenarios.Run(scenario)], **steps)


@query(_cells("a"))
def scenario_a(spark, sf_dir):
    return rounded(measures.rates(scenarios.run(spark, sf_dir, "a")))


@query(_cells("b"))
def scenario_b(spark, sf_dir):
    return rounded(measures.rates(scenarios.run(spark, sf_dir, "b")))


@query(sql(f"{RATES} FROM c", "truth", "enc", p=f"SELECT a.group_id, a.entity_id = b.entity_id AS truth, CASE WHEN a.n_ones + b.n_ones = 0 THEN 0 ELSE 2.0 * {COMMON} / (a.n_ones + b.n_ones) END AS sim FROM enc a JOIN enc b ON a.party = 'A' AND b.party = 'B' AND a.group_id = b.group_id", c=_conf("p")))
def scenario_all_pairs(spark, sf_dir):
    """All pairs of a group, those that cannot be alike by bounds: the ceiling of cost and recall."""
    rows = written(encode.encoded_values(written(people.parties(spark, sf_dir), "records"), more=("suburb", "surname")), "encoded")
    own = pairs.candidates(*pairs.split(block.none(rows)), entities=True)
    found = allpairs.counts(rows, own, DEFAULT.threshold, ["suburb", "surname"])
    return rounded(measures.rates(measures.with_truth(found, measures.truth_pairs(*pairs.split(rows)))))


_KANON = "SELECT bin, blk.* EXCLUDE (label), bin AS label FROM blk JOIN (SELECT party, table_no, label, floor(coalesce(sum(n) OVER (PARTITION BY party, table_no ORDER BY label ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) / 10)::BIGINT AS bin FROM (SELECT party, table_no, label, count(*) AS n FROM blk GROUP BY ALL)) USING (party, table_no, label)"


@query(sql("SELECT party, table_no, label, count(*) AS n FROM merged GROUP BY ALL", "blk", merged=_KANON))
def scenario_k_anonymous(spark, sf_dir):
    blocked = _blocked(spark, sf_dir)
    merged = block.k_anonymous(blocked, 10).select("party", *block.BIN, "bin")
    return blocked.join(merged, ["party", *block.BIN]).groupBy("party", "table_no", F.col("bin").alias("label")).agg(F.count("*").alias("n"))


@query(sql(f"SELECT 'b2' AS scenario, *, real + fake AS pairs, {rate('fake', 'real')} AS overhead FROM ({_COST}) UNION ALL SELECT 'b1', group_id, real, 0::BIGINT, real, 0.0 FROM ({_COST})", "counts"))
def scenario_cost(spark, sf_dir):
    stats = scenarios.bench(spark, sf_dir).stats
    b2 = measures.cost(noise.dummy_counts(stats, _groups(spark))).select(F.lit("b2").alias("scenario"), "*")
    b1 = measures.cost(stats.withColumn("m", F.lit(0))).select(F.lit("b1").alias("scenario"), "*")
    return rounded(b2.unionByName(b1))


@query("WITH r AS (SELECT p_partkey::BIGINT AS entity_id, p_brand, p_type, p_size, lower(substr(p_type, 1, 1)) AS group_id, (('0x' || substr(md5('7|part|' || p_partkey::VARCHAR), 1, 13))::BIGINT % 3) AS lot FROM part) SELECT a.group_id, count(*) AS pairs, count(*) FILTER (WHERE a.entity_id = b.entity_id) AS true_pairs FROM r a JOIN r b ON a.lot <> 2 AND b.lot <> 1 AND a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_size = b.p_size GROUP BY a.group_id")
def part_records(spark, sf_dir):
    rows = people.parts_as_records(spark, sf_dir)
    key = ["p_brand", "p_type", "p_size"]
    a = rows.where("party = 'A'").select(*key, "group_id", F.col("entity_id").alias("ea"))
    b = rows.where("party = 'B'").select(*key, F.col("entity_id").alias("eb"))
    return a.join(b, key).groupBy("group_id").agg(F.count("*").alias("pairs"), F.count_if(F.col("ea") == F.col("eb")).alias("true_pairs"))


# Other workloads and protected features of the noisy baseline.

_AGE = "CASE WHEN age <= 45 THEN 'young' ELSE 'old' END"
_RECS = "SELECT *, {group} AS group_id, party || '-' || entity_id::VARCHAR AS rec_id FROM (SELECT *, 'A' AS party FROM people WHERE lot <> 2 UNION ALL SELECT * {change}, 'B' AS party FROM people WHERE lot <> 1)"
_DIRTY = _RECS.format(group="gender", change="REPLACE (" + ", ".join(_edit_sql(c, i) for i, c in enumerate(("given", "surname", "suburb", "postcode"))) + ")")
_BIASED = _RECS.format(group="gender", change="REPLACE (" + ", ".join(map(_fresh_sql, ("surname", "suburb", "postcode"))) + ")")


def _rates_of(spark, sf_dir, name, **options):
    return rounded(measures.rates(scenarios.run(spark, sf_dir, name, **options)))


@query(sql(f"{RATES} FROM nconf", "nconf", recs=_RECS.format(group=_AGE, change="")))
def scenario_b2_age(spark, sf_dir):
    return _rates_of(spark, sf_dir, "b2", features=("age_band",))


@query(sql(f"{RATES} FROM nconf", "nconf", recs=_RECS.format(group=f"gender || '/' || {_AGE}", change=""), counts=noise_sql("4.0").replace("STATS", "stats")))
def scenario_b2_product(spark, sf_dir):
    return _rates_of(spark, sf_dir, "b2", features=("gender", "age_band"))


@query(sql(f"{RATES} FROM nconf", "nconf", recs=_DIRTY))
def scenario_b2_dirty(spark, sf_dir):
    return _rates_of(spark, sf_dir, "b2", flavour="dirty")


@query(sql(f"{RATES} FROM conf", "conf", recs=_DIRTY))
def scenario_b1_dirty(spark, sf_dir):
    return _rates_of(spark, sf_dir, "b1", flavour="dirty")


@query(sql(f"{RATES} FROM nconf", "nconf", recs=_BIASED))
def scenario_b2_biased(spark, sf_dir):
    return _rates_of(spark, sf_dir, "b2", flavour="biased")


@query(sql(f"{RATES} FROM conf", "conf", recs=_BIASED))
def scenario_b1_biased(spark, sf_dir):
    return _rates_of(spark, sf_dir, "b1", flavour="biased")


@query(sql(f"{RATES} FROM nconf", "nconf", enc=f"SELECT *, ({ONES})::INTEGER AS n_ones FROM ({encoded('recs', CENSUS)})"))
def scenario_b2_census(spark, sf_dir):
    return _rates_of(spark, sf_dir, "b2", flavour="census")


@query(sql(f"{RATES} FROM nconf", "nconf", counts=noise_sql("0.2").replace("STATS", "stats")))
def scenario_b2_small_budget(spark, sf_dir):
    return _rates_of(spark, sf_dir, "b2", eps=0.1)


@query(sql(f"{RATES} FROM nconf", "nconf", counts=noise_sql("20.0").replace("STATS", "stats")))
def scenario_b2_large_budget(spark, sf_dir):
    return _rates_of(spark, sf_dir, "b2", eps=10.0)


@query(_cells("a", recs=_BIASED))
def scenario_a_biased(spark, sf_dir):
    return _rates_of(spark, sf_dir, "a", flavour="biased")


@query(_cells("b", recs=_BIASED))
def scenario_b_biased(spark, sf_dir):
    return _rates_of(spark, sf_dir, "b", flavour="biased")


@query()
def scenario_b2_logistic(spark, sf_dir):
    """Trained on original pairs of a split by record, judged on the noisy ones."""
    return _rates_of(spark, sf_dir, "b2", flavour="dirty", classifier="logistic")


@query(sql(f"SELECT round(sum(a * b), 4) AS pairs FROM (SELECT table_no, label, coalesce(sum(n + {_MEAN}) FILTER (WHERE party = 'A'), 0) AS a, coalesce(sum(n + {_MEAN}) FILTER (WHERE party = 'B'), 0) AS b FROM stats GROUP BY ALL)", "stats"))
def expected_candidates(spark, sf_dir):
    """Expected pairs of noisy bins, all groups of a bin together."""
    stats = scenarios.bench(spark, sf_dir).stats.withColumn("size", F.col("n") + theory.capped_mean(F.col("n"), F.lit(2.0)))
    side = lambda p: F.coalesce(F.sum(F.when(F.col("party") == p, F.col("size"))), F.lit(0.0))
    return stats.groupBy(*block.BIN).agg(side("A").alias("a"), side("B").alias("b")).agg(F.round(F.sum(F.col("a") * F.col("b")), 4).alias("pairs"))


@query(sql("SELECT group_id, round(" + _PFP.replace("F", "0.2::DOUBLE") + " * ((na + nb) / 4.0 + bins / 16.0), 4) AS false_matches FROM g", "conf", "stats", g=_G))
def dummy_fp_expected(spark, sf_dir):
    """Upper bound of false matches by dummies: every dummy pair taken for one with the source."""
    cut = 300 * 0.8 * 0.2 / (2 * (1 - 0.8) * (1 - 0.2))
    p = 0.5 * (1 - theory.erf(F.lit((cut - 150) / 150.0**0.5)))
    fake = (F.col("na") + F.col("nb")) / 4 + F.col("bins") / 16
    return _group_table(spark, sf_dir).select("group_id", F.round(p * fake, 4).alias("false_matches"))


@query(sql("SELECT party, group_id, count(*) FILTER (WHERE same = 1) AS unique_bins, count(*) FILTER (WHERE n < 2) AS rare_bins, count(*) AS bins FROM (SELECT *, count(*) OVER (PARTITION BY party, table_no, n) AS same FROM (SELECT party, table_no, label, group_id, n + m AS n FROM counts)) GROUP BY ALL", "counts"))
def exposure_noisy_bins(spark, sf_dir):
    noisy = noise.dummy_counts(scenarios.bench(spark, sf_dir).stats, _groups(spark)).select(*noise.KEYS, (F.col("n") + F.col("m")).alias("n"))
    return measures.exposure(noisy)


@query(sql(f"SELECT group_id, count(*) AS sampled, count(*) FILTER (WHERE sim > 0.8 AND NOT truth) AS fp, count(*) FILTER (WHERE sim <= 0.8 AND truth) AS fn FROM pairs WHERE {u('sample', 'id_a', 'id_b')} < 0.5 GROUP BY group_id", "pairs"))
def sample_rates(spark, sf_dir):
    """Original errors on a keyed half of the pairs."""
    own = classify.threshold(scenarios.plain_pairs(scenarios.bench(spark, sf_dir))).where(rng.uniform(DEFAULT.seed, "sample", "id_a", "id_b") < 0.5)
    return own.groupBy("group_id").agg(F.count("*").alias("sampled"), F.count_if(F.col("pred") & ~F.col("truth")).alias("fp"), F.count_if(~F.col("pred") & F.col("truth")).alias("fn"))


@query()
def bloom_rounds(spark, sf_dir):
    """Filters of two encoding rounds, and how full they are."""
    return rounded(encode.fill_stats(encode.encoded(people.parties(spark, sf_dir), rounds=2)))


@query()
def tuned_both(spark, sf_dir):
    """Budgets first, then flips."""
    stats = scenarios.group_stats(scenarios.bench(spark, sf_dir, keep=True))
    found = allocate.both(stats, 1.0, 0.4)
    return spark.createDataFrame([(s.group_id, round(float(e), 6), float(f)) for s, e, f in zip(stats, found.eps, found.flip, strict=True)], "group_id string, eps double, flip double")
