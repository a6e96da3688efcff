"""The scenarios that the method is compared in, from records to measures.

A bench holds the blocked records of both parties, written once. Any number of runs (a scenario with its budget and
flip) is judged in one pass: pairs of originals are compared once for all runs, every run adds the pairs of its own dummies
only, and what comes out is one row of counts per run, classifier and group.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fairlink.functions import bits, rng, theory
from fairlink.operators import allocate, block, cells, classify, encode, hinge, measures, noise, pairs, tiles
from fairlink.settings import DEFAULT, Linkage
from fairlink.sources import people
from fairlink.sources.steps import written

SCENARIOS = ("b1", "b2", "b3", "a", "b")
LEARNED = ("logistic", "logistic_plain", "tree", "forest", "svm")
FORESTS = {"tree": 1, "forest": cells.TREES}


@dataclass(frozen=True)
class Bench:
    """Blocked records of both parties, their bin sizes and true pairs."""

    blocked: DataFrame
    stats: DataFrame
    truth: DataFrame
    settings: Linkage
    attributes: int = 0
    alike: bool = False  # many records of a party are equal: they are compared as one, with their number


@dataclass(frozen=True)
class Run:
    """b1 no noise, b2 equal knobs, b3 noise without groups, a tuned flips, b tuned budgets, cost budgets for least cost."""

    scenario: str
    eps: float = 1.0
    flip: float = 0.4


def bench(
    spark: SparkSession, sf_dir: str, flavour: str = "clean", features: tuple[str, ...] = ("gender",), settings: Linkage = DEFAULT,
    keep: bool = False, attributes: bool = False, rounds: int = 1, share: float = 1.0,
) -> Bench:
    """With `keep` the blocked rows are written, for plans that read them more than once."""
    records = people.parties(spark, sf_dir, flavour, features, share)
    if flavour == "census":
        encoded = encode.encoded_census(records, settings, rounds, attributes)
    elif keep:
        encoded = encode.encoded_values(written(records, "records"), settings, rounds, attributes)
    else:
        encoded = encode.encoded(records, settings, False, rounds, attributes)
    blocked = block.bit_labels(encoded, settings)
    if keep:
        blocked = written(blocked, "blocked")
    stats = block.bin_stats(blocked)
    if keep:
        stats = written(stats, "bins")
    truth = measures.truth_pairs(*pairs.split(blocked.where("table_no = 0") if keep else encoded))
    return Bench(blocked, stats, truth, settings, len(encode.ATTRIBUTES[flavour == "census"]) if attributes else 0, flavour == "census")


def plain_pairs(b: Bench) -> DataFrame:
    return pairs.candidates(*pairs.split(b.blocked), settings=b.settings)


def kinds(rows: DataFrame) -> DataFrame:
    """Equal records of a bin as one, with their number; those of either half stay apart."""
    half = rows.withColumn("source_a", F.col("rec_id")).withColumn("half", tested())
    keys = [c for c in half.columns if c not in ("rec_id", "entity_id", "source_a")]
    return half.groupBy(*keys).agg(F.count("*").alias("copies"), F.min("rec_id").alias("rec_id"))


def kind_pairs(b: Bench) -> DataFrame:
    """The pairs of originals by group, half, truth and similarities, with their number in copies.

    All pairs are those of kinds. True ones are found by entity, record by record, and are taken from the others.
    """
    a, other = pairs.split(kinds(b.blocked))
    every = pairs.candidates(a, other.drop("half").groupBy(*[c for c in other.columns if c not in ("half", "copies", "rec_id")]).agg(F.sum("copies").alias("copies"), F.min("rec_id").alias("rec_id")), settings=b.settings)
    own = pairs.candidates(*pairs.split(b.blocked), settings=b.settings, entities=True).withColumn("half", tested())
    keys = ["group_id", "half", *features_of(b)]
    rows = [(every, F.lit(False), F.col("copies")), (own, F.lit(False), F.lit(-1).cast("long")), (own, F.lit(True), F.lit(1).cast("long"))]
    made = reduce(DataFrame.unionByName, [r.select(*keys, t.alias("truth"), n.alias("copies")) for r, t, n in rows])
    return made.groupBy(*keys, "truth").agg(F.sum("copies").alias("copies")).where("copies <> 0")


def kind_fakes(b: Bench, dummies: DataFrame, settings: Linkage) -> DataFrame:
    """The pairs with a dummy, originals as kinds."""
    return pairs.fakes(kinds(b.blocked), dummies.withColumn("source_a", F.col("parent_id")).withColumn("half", tested()).withColumn("copies", F.lit(1).cast("long")), settings)


def tiled(b: Bench) -> DataFrame:
    """The bins of originals as matrices: their pairs are too many to be written."""
    return tiles.written_tiles(b.blocked.withColumn("source_a", F.col("rec_id")), tested(), b.settings.label_tables, b.attributes)


def threshold_counts(b: Bench, made: DataFrame) -> DataFrame:
    t = b.settings.threshold
    return tiles.judged(made, b.settings.label_tables, b.attributes, lambda x: x[-1] > t)


def original_pairs(b: Bench) -> DataFrame:
    return kind_pairs(b) if b.alike else plain_pairs(b)


def group_sizes(b: Bench) -> DataFrame:
    """Rows of each party per group, and the number of bins."""
    side = lambda p: F.sum(F.when(F.col("party") == p, F.col("n")).otherwise(0))
    bins = b.stats.select(*block.BIN).distinct().agg(F.count("*").alias("bins"))
    return b.stats.groupBy("group_id").agg(side("A").alias("na"), side("B").alias("nb")).crossJoin(F.broadcast(bins))


def group_stats(b: Bench, sample: float = 1.0, found: DataFrame | None = None) -> list[allocate.GroupStats]:
    """Sizes and original error rates of the groups; one row a group reaches the driver.

    With a sample below 1 the rates come from a keyed share of the original pairs; `found` are counts made before.
    """
    if found is None:
        own = kind_pairs(b) if b.alike and sample >= 1 else plain_pairs(b).where(rng.uniform(b.settings.seed, "sample", "id_a", "id_b") < sample)
        found = measures.confusion(classify.threshold(own, b.settings.threshold))
    made = []
    for r in group_sizes(b).join(found, "group_id", "left").orderBy("group_id").collect():
        tp, fp, tn, fn = (r[c] or 0 for c in ("tp", "fp", "tn", "fn"))
        made.append(allocate.GroupStats(r["group_id"], r["na"], r["nb"], r["bins"], fp / sample, (fp + tn) / sample, fn / max(1, fn + tp)))
    return made


def tuned(run: Run, groups: list[str], stats: list[allocate.GroupStats] | None) -> allocate.Knobs | None:
    n = len(groups)
    equal = theory.split_equal(run.eps, n)
    if run.scenario == "b2":
        return allocate.Knobs((equal,) * n, (run.flip,) * n, float("nan"), float("nan"))
    if run.scenario == "a":
        return allocate.flips(stats, equal)
    if run.scenario in ("b", "cost"):
        return allocate.budgets(stats, run.eps, run.flip, "cost" if run.scenario == "cost" else "fairness")
    return None


def knobs_of_runs(spark: SparkSession, b: Bench, runs: list[Run], sample: float = 1.0, found: DataFrame | None = None) -> DataFrame:
    """(run, group_id, eps, flip) of the runs with group noise: as many rows as runs and groups."""
    groups = [r[0] for r in b.stats.select("group_id").distinct().orderBy("group_id").collect()]
    stats = group_stats(b, sample, found) if any(r.scenario in ("a", "b", "cost") for r in runs) else None
    rows = []
    for i, run in enumerate(runs):
        found = tuned(run, groups, stats)
        if found:
            rows += [(i, g, float(e), float(f)) for g, e, f in zip(groups, found.eps, found.flip, strict=True)]
    return spark.createDataFrame(rows, "run int, group_id string, eps double, flip double")


def knobs_of(spark: SparkSession, stats: list[allocate.GroupStats], found: allocate.Knobs) -> DataFrame:
    rows = [(s.group_id, float(e), float(f)) for s, e, f in zip(stats, found.eps, found.flip, strict=True)]
    return spark.createDataFrame(rows, "group_id string, eps double, flip double")


def dummies_of_runs(spark: SparkSession, b: Bench, runs: list[Run], settings: Linkage, sample: float = 1.0, found: DataFrame | None = None) -> DataFrame:
    made = noise.feature_runs(b.blocked, b.stats, knobs_of_runs(spark, b, runs, sample, found), settings)
    blind = [(i, float(r.eps), float(r.flip)) for i, r in enumerate(runs) if r.scenario == "b3"]
    if blind:
        more = noise.record_runs(b.blocked, spark.createDataFrame(blind, "run int, eps double, flip double"), settings)
        made = made.select(*more.columns).unionByName(more)
    return made


def features_of(b: Bench) -> list[str]:
    """What learned classifiers see: the similarity of each attribute and of the whole record."""
    return [*(f"sim{j}" for j in range(b.attributes)), "sim"]


def tested() -> F.Column:
    """Pairs of the half of A's records that no learner is trained on; a dummy belongs to its source's half."""
    return rng.uniform(DEFAULT.seed, "split", "source_a") >= 0.5


def half(rows: DataFrame) -> DataFrame:
    """Rows with the mark of the test half, which kinds carry."""
    return rows if "half" in rows.columns else rows.withColumn("half", tested())


def learner(b: Bench, own: DataFrame, kind: str):
    """A function that adds pred and score: trained on the original pairs of the training half; balanced by class and group, but for the plain one."""
    train = half(own).where("NOT half")
    if kind == "logistic":
        train = classify.group_weights(train, ["truth", "group_id"])
    name, weight = kind.split("_")[0], "weight" if kind == "logistic" else None
    if "copies" not in train.columns:
        model = classify.model(name, train, features_of(b), weight=weight)
        return lambda rows: classify.predict(model, rows, features_of(b))
    return classify.logistic_of_copies(train, features_of(b), weight)


def grid(
    spark: SparkSession, sf_dir: str, runs: list[Run], flavour: str = "clean", features: tuple[str, ...] = ("gender",), classifiers: tuple[str, ...] = ("threshold",),
    settings: Linkage = DEFAULT, seed: int | None = None, rounds: int = 1, share: float = 1.0, sample: float = 1.0, b: Bench | None = None, found: DataFrame | None = None,
) -> DataFrame:
    """Counts of every run, classifier and group: scenario, eps, flip, classifier, group_id, tp, fp, tn, fn, real, fake.

    Learned classifiers are judged on the test half, truth included. `seed` is that of the noise,
    `found` are the threshold's counts of originals where they are known.
    """
    learned = any(c in LEARNED for c in classifiers)
    b = b or bench(spark, sf_dir, flavour, features, settings, True, learned, rounds, share)
    s = b.settings if seed is None else replace(b.settings, seed=seed)
    if b.alike and not {*classifiers} <= {"threshold", "logistic", "logistic_plain"}:
        b = replace(b, alike=False)  # other learners count rows, not weights
    # Counts of originals do not depend on the noise: one pass each, or those of a sweep made before.
    size = (b.settings.label_tables, b.attributes)
    matrices = not b.alike and sample >= 1 and (found is not None or set(classifiers) <= {"logistic", "logistic_plain", "svm", *FORESTS})
    made = tiled(b) if matrices and learned else None
    trees = {c: cells.fitted(made, *size, FORESTS[c]) for c in classifiers if c in FORESTS} if matrices else {}
    if None in trees.values():  # too many cells for a task
        matrices, made = False, None
    own = None if matrices else original_pairs(b)
    if made is not None and any(r.scenario in ("a", "b", "cost") for r in runs):
        found = threshold_counts(b, made)
    noisy = any(r.scenario != "b1" for r in runs)
    fake = (kind_fakes if b.alike else lambda x, *more: pairs.fakes(x.blocked, *more))(b, written(dummies_of_runs(spark, b, runs, s, sample, found), "dummies"), s) if noisy else None
    if own is not None and (learned or b.alike):
        own = written(own, "pairs")
    out = []
    for kind in classifiers:
        plain, other, truth = own, fake, b.truth
        if kind in LEARNED:
            truth = truth.withColumn("source_a", F.col("id_a")).where(tested())
        if kind in trees and matrices:
            grown = trees[kind]
            before = tiles.judged(made, *size, cells.Verdict(*grown), half=True, reader=cells.Reader(grown[0]))
            judge = lambda rows, grown=grown: cells.scored(half(rows).where("half"), *grown, features_of(b))
        elif kind in LEARNED and matrices:
            beta = hinge.fitted(made, *size) if kind == "svm" else tiles.logistic(made, *size, kind == "logistic")
            before = tiles.judged(made, *size, lambda x, beta=beta: beta[0] + beta[1:] @ x > 0, half=True)
            judge = lambda rows, beta=beta: tiles.scored(half(rows).where("half"), beta, features_of(b))
        elif kind in LEARNED:
            model = learner(b, own, kind)
            judge = lambda rows, model=model: model(half(rows).where("half"))
            before = measures.confusion(judge(plain))
        else:
            judge = lambda rows: classify.threshold(rows, s.threshold)
            before = found if matrices else measures.confusion(judge(plain))
        counts = measures.with_truth(before, truth).join(before.select("group_id", (F.col("tp") + F.col("fp") + F.col("tn") + F.col("fn")).alias("real")), "group_id", "left")
        if other is not None:
            added = judge(other).groupBy("run", "group_id").agg(measures.number(other, F.col("pred")).alias("dfp"), measures.number(other, ~F.col("pred")).alias("dtn"))
        else:
            added = spark.createDataFrame([], "run int, group_id string, dfp long, dtn long")
        named = spark.createDataFrame([(i, r.scenario, float(r.eps), float(r.flip)) for i, r in enumerate(runs)], "run int, scenario string, eps double, flip double")
        # Counts per group and runs: small tables whatever the data.
        joined = counts.crossJoin(F.broadcast(named)).join(added, ["run", "group_id"], "left")
        zero = lambda c: F.coalesce(F.col(c), F.lit(0).cast("long"))
        out.append(joined.select(
            "scenario", "eps", "flip", F.lit(kind).alias("classifier"), "group_id", "tp", (F.col("fp") + zero("dfp")).alias("fp"), (F.col("tn") + zero("dtn")).alias("tn"), "fn",
            zero("real").alias("real"), (zero("dfp") + zero("dtn")).alias("fake"),
        ))
    return reduce(DataFrame.unionByName, out)


def summaries(counts: DataFrame) -> DataFrame:
    """One row a run and classifier: error rates, F*, fairness and comparisons."""
    keys = ["scenario", "eps", "flip", "classifier"]
    size = counts.groupBy(*keys).agg((F.sum("real") + F.sum("fake")).alias("comparisons"), F.sum("fake").alias("fake"))
    return measures.by_run(counts, keys).join(size, keys)


def run(spark: SparkSession, sf_dir: str, name: str, eps: float = 1.0, flip: float = 0.4, flavour: str = "clean", features: tuple[str, ...] = ("gender",), classifier: str = "threshold", settings: Linkage = DEFAULT, **options) -> DataFrame:
    """Counts per group of one scenario: group_id, tp, fp, tn, fn."""
    found = grid(spark, sf_dir, [Run(name, eps, flip)], flavour, features, (classifier,), settings, **options)
    return found.select("group_id", "tp", "fp", "tn", "fn")


def sweep(spark: SparkSession, sf_dir: str, names=SCENARIOS, eps=(0.1, 1.0, 10.0), flavours=("clean",), classifiers=("threshold",), seeds=(None,), flip: float = 0.4, features: tuple[str, ...] = ("gender",), **options) -> DataFrame:
    """One row per flavour, scenario, budget and classifier, averaged over the noise's seeds. Each flavour is blocked once."""
    out = []
    for flavour in flavours:
        b = bench(spark, sf_dir, flavour, features, keep=True, attributes=any(c in LEARNED for c in classifiers))
        runs = [Run(n, e, flip) for n in names for e in eps]
        found = threshold_counts(b, tiled(b)) if tuple(classifiers) == ("threshold",) and not b.alike and options.get("sample", 1.0) >= 1 else None
        for seed in seeds:
            out.append(summaries(grid(spark, sf_dir, runs, flavour, features, classifiers, seed=seed, b=b, found=found, **options)).withColumn("flavour", F.lit(flavour)))
    every = reduce(DataFrame.unionByName, out)
    keys = ["flavour", "scenario", "eps", "flip", "classifier"]
    return every.groupBy(*keys).agg(*(F.avg(c).alias(c) for c in every.columns if c not in keys)) if len(seeds) > 1 else every


def dummy_fp_curve(spark: SparkSession, b: Bench, steps: int = 50, eps: float | None = None) -> DataFrame:
    """flip, dummies, measured: the share of dummies above the threshold with their own source, for all flips 0, 1/steps, .., 1.

    A bit's draw does not depend on the flip, so one pass tells from which flip on it flips: counts of flipped ones and
    zeros by step, summed up along the steps, give every flip's similarity.
    """
    s = b.settings if eps is None else replace(b.settings, eps=eps)
    groups = [r[0] for r in b.stats.select("group_id").distinct().orderBy("group_id").collect()]
    chosen = noise.picked(b.blocked, noise.dummy_counts(b.stats, noise.equal_knobs(spark, groups, s), s), settings=s)
    drawn = chosen.select("rec_id", "table_no", "n_ones", *bits.names(), F.explode(F.sequence(F.lit(0), F.lit(s.n_bits - 1))).alias("bit"))
    word, place = F.floor(F.col("bit") / 60).cast("int"), F.col("bit") % 60
    key = F.concat_ws("|", F.lit(f"{s.seed}|flip"), "rec_id", F.col("table_no").cast("string"), word.cast("string"), F.floor(place / 2).cast("string"))
    u = (F.when(place % 2 == 0, rng.whole(key, 1)).otherwise(rng.whole(key, rng.DIGITS + 1)) + 0.5) / rng.RANGE
    own = F.expr("array(w0, w1, w2, w3, w4)")
    one = F.call_function("shiftright", F.get(own, word), place.cast("int")).bitwiseAND(F.lit(1).cast("long"))
    # The first step whose flip is above the draw.
    step = F.floor(u * steps).cast("int") + 1
    cells = drawn.select("rec_id", "table_no", "n_ones", step.alias("step"), one.alias("one")).groupBy("rec_id", "table_no", "n_ones", "step").agg(F.sum("one").alias("ones"), F.sum(1 - F.col("one")).alias("zeros"))
    rows = cells.groupBy("rec_id", "table_no", "n_ones").agg(F.map_from_entries(F.collect_list(F.struct("step", F.struct("ones", "zeros")))).alias("at"))  # at most steps + 1 entries
    flat = rows.select("n_ones", F.posexplode(_running(steps)).alias("step", "c"))
    kept = F.col("n_ones") - F.col("c.ones")
    sim = bits.dice(kept, F.col("n_ones"), kept + F.col("c.zeros"))
    return flat.groupBy((F.col("step") / steps).alias("flip")).agg(F.count("*").alias("dummies"), F.avg((sim > s.threshold).cast("double")).alias("measured"))


def _running(steps: int) -> F.Column:
    """Of every step the flipped ones and zeros up to it."""
    zero = F.struct(F.lit(0).cast("long").alias("ones"), F.lit(0).cast("long").alias("zeros"))
    at = lambda i: F.coalesce(F.try_element_at(F.col("at"), i), zero)
    add = lambda acc, i: F.struct((acc["last"]["ones"] + at(i)["ones"]).alias("ones"), (acc["last"]["zeros"] + at(i)["zeros"]).alias("zeros"))
    start = F.struct(zero.alias("last"), F.array(zero).alias("all"))
    grown = lambda acc, i: F.struct(add(acc, i).alias("last"), F.concat(acc["all"], F.array(add(acc, i))).alias("all"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, grown, lambda acc: acc["all"])
