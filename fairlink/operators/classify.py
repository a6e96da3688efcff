"""Classifiers of candidate pairs."""

from __future__ import annotations

from pyspark.ml.classification import DecisionTreeClassifier, LinearSVC, LogisticRegression, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fairlink.functions import rng
from fairlink.operators import measures
from fairlink.settings import DEFAULT


def threshold(pairs: DataFrame, t: float = DEFAULT.threshold, column: str = "sim") -> DataFrame:
    """A match is strictly above the threshold."""
    return pairs.withColumn("pred", F.col(column) > t)


def split(pairs: DataFrame, share: float = 0.5, seed: int = DEFAULT.seed, key: str = "id_a") -> tuple[DataFrame, DataFrame]:
    """Training and test pairs by a keyed draw of A's record, so that no record is in both."""
    u = rng.uniform(seed, "split", key)
    return pairs.where(u < share), pairs.where(u >= share)


def model(kind: str, train: DataFrame, features: list[str], label: str = "truth", weight: str | None = None):
    """A fitted learner: logistic, tree, forest or svm. The weight column balances classes or groups."""
    made = {
        "logistic": LogisticRegression(maxIter=50, regParam=1e-3),
        "tree": DecisionTreeClassifier(maxDepth=5, seed=7),
        "forest": RandomForestClassifier(numTrees=20, maxDepth=5, seed=7),
        "svm": LinearSVC(maxIter=50, regParam=1e-3),
    }[kind]
    if weight:
        made = made.setWeightCol(weight)
    rows = VectorAssembler(inputCols=features, outputCol="features").transform(train.withColumn("label", F.col(label).cast("double")))
    return made.fit(rows)


def logistic_of_copies(train: DataFrame, features: list[str], weight: str | None = None):
    """The logistic classifier of rows that stand for as many pairs as copies says, as a function that adds pred and score.

    Features are scaled by the deviations that the single pairs would have, for the learner's own depend on how weights are dealt to rows.
    """
    w = F.col(weight) if weight else F.lit(1.0)
    n, x = F.col("copies"), {c: F.col(c) for c in features}
    sums = train.agg(F.sum(n * w).alias("w"), F.sum(n * w * w).alias("w2"), *(F.sum(n * w * v).alias(f"{c}_1") for c, v in x.items()))
    first = sums.first()
    means = {c: (first[f"{c}_1"] or 0.0) / (first["w"] or 1.0) for c in features}
    spread = train.agg(*(F.sum(n * w * (v - means[c]) * (v - means[c])).alias(c) for c, v in x.items())).first()
    free = (first["w"] or 1.0) - (first["w2"] or 0.0) / (first["w"] or 1.0)
    deviation = {c: max(0.0, (spread[c] or 0.0) / free) ** 0.5 if free > 0 else 0.0 for c in features}
    scaled = lambda rows: rows.withColumns({f"_{c}": v / (deviation[c] if deviation[c] > 1e-9 else 1.0) for c, v in x.items()})
    names = [f"_{c}" for c in features]
    made = LogisticRegression(maxIter=50, regParam=1e-3, standardization=False, weightCol="_weight")
    rows = scaled(train).withColumn("label", F.col("truth").cast("double")).withColumn("_weight", n * w)
    fitted = made.fit(VectorAssembler(inputCols=names, outputCol="features").transform(rows))
    return lambda pairs: predict(fitted, scaled(pairs), names).drop(*names)


def predict(fitted, pairs: DataFrame, features: list[str]) -> DataFrame:
    """Adds pred, and score where the model has a probability."""
    out = fitted.transform(VectorAssembler(inputCols=features, outputCol="features").transform(pairs))
    if "probability" in out.columns:
        out = out.withColumn("score", F.get(vector_to_array("probability"), F.lit(1)))
    return out.withColumn("pred", F.col("prediction") == 1.0).drop("features", "rawPrediction", "probability", "prediction")


def group_weights(train: DataFrame, by: list[str]) -> DataFrame:
    """Adds weight: rows of every combination of `by` weigh the same in sum."""
    sizes = train.groupBy(*by).agg(measures.number(train).alias("_n"))
    total = train.agg(measures.number(train)).first()[0] or 0
    cells = sizes.count()
    return train.join(F.broadcast(sizes), by).withColumn("weight", F.lit(total / max(1, cells)) / F.col("_n")).drop("_n")


def mutual_best(pairs: DataFrame) -> DataFrame:
    """Pairs that are each other's best; ties by the smaller id."""
    best = lambda own, other: F.row_number().over(Window.partitionBy(own).orderBy(F.desc("sim"), other))
    return pairs.withColumn("_a", best("id_a", "id_b")).withColumn("_b", best("id_b", "id_a")).where("_a = 1 AND _b = 1").drop("_a", "_b")
