"""Classifiers over rows (x array of longs in millionths, y, w): the four of MLlib, and naive Bayes in closed form.

All score a column p in [0, 1]; all take instance weights.
"""

from __future__ import annotations

from pyspark.ml.classification import DecisionTreeClassifier, LinearSVC, LogisticRegression, RandomForestClassifier
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ertransfer.functions.vectors import MICRO

#: Least variance of a feature of the naive Bayes, in squared millionths.
FLOOR = 1e4
#: The same settings for every algorithm that is compared.
REG, STEPS, TREES, DEPTH, SEED = 1e-3, 50, 50, 8, 7
ROWS_A_TASK = 20_000
KINDS = ("lr", "svm", "dt", "rf")


def make_classifier(kind: str):
    """The MLlib estimator of a kind, over columns features, y and w."""
    common = {"featuresCol": "features", "labelCol": "y", "weightCol": "w"}
    made = {
        "lr": lambda: LogisticRegression(regParam=REG, maxIter=STEPS, standardization=False, **common),
        "svm": lambda: LinearSVC(regParam=REG, maxIter=STEPS, standardization=False, **common),
        "dt": lambda: DecisionTreeClassifier(maxDepth=DEPTH, seed=SEED, **common),
        "rf": lambda: RandomForestClassifier(numTrees=TREES, maxDepth=DEPTH, seed=SEED, **common),
    }
    if kind not in made:
        raise ValueError(f"classifier {kind} is none of {', '.join(made)}, gnb")
    return made[kind]()


def _features(x: Column, scale: float = MICRO) -> Column:
    return array_to_vector(F.transform(x, lambda v: v / float(scale)))


def common_scale(train: DataFrame) -> float:
    """Root mean square of the features that are not zero.

    One scale for all places: scaling each by its own spread would blow up the blocks that few rows fill, and with them
    what the target's few labels say.
    """
    v = F.col("v").cast("double")
    found = train.select(F.explode("x").alias("v")).where("v <> 0").agg(F.sqrt(F.avg(v * v))).first()[0]
    return found or float(MICRO)


class Fitted:
    """A fitted classifier; ``score`` adds p to a table with the features in ``column``."""

    def __init__(self, kind: str, model, scale: float = MICRO):
        self.kind, self.model, self.scale = kind, model, scale

    def score(self, table: DataFrame, column: str = "x", name: str = "p") -> DataFrame:
        if self.kind == "gnb":
            return table.withColumn(name, bayes_probability(self.model, F.col(column)))
        made = self.model.transform(table.withColumn("features", _features(F.col(column), self.scale)))
        if self.kind == "svm":  # has a margin only
            p = 1 / (1 + F.exp(-vector_to_array("rawPrediction")[1]))
        else:
            p = vector_to_array("probability")[1]
        return made.withColumn("_p", p).select(*table.columns, F.col("_p").alias(name))


def fit(kind: str, train: DataFrame) -> Fitted:
    """Trains ``kind`` (lr, svm, dt, rf or gnb) on rows (x, y, w); both classes must occur."""
    if kind == "gnb":
        return Fitted(kind, fit_bayes(train))
    scale = common_scale(train) if kind in ("lr", "svm") else float(MICRO)
    rows = train.select(_features(F.col("x"), scale).alias("features"), F.col("y").cast("double").alias("y"), F.col("w").cast("double").alias("w")).cache()
    try:
        counts = {r.y: r.n for r in rows.groupBy("y").agg(F.count("*").alias("n")).collect()}
        if len(counts) != 2:
            raise ValueError("training pairs of both classes are needed")
        # Every step of the optimiser is a job: a few thousand rows a task outweigh its start.
        few = rows.coalesce(sum(counts.values()) // ROWS_A_TASK + 1)
        return Fitted(kind, make_classifier(kind).fit(few), scale)
    finally:
        rows.unpersist()


# --- naive Bayes -------------------------------------------------------------------------------------------------


def fit_bayes(train: DataFrame) -> dict:
    """Weighted Gaussian naive Bayes of (x, y, w): {y: (prior, means, variances)}; a row a class and place reaches the driver."""
    long = train.select("y", "w", F.posexplode("x").alias("i", "v"))
    v = F.col("v").cast("double")
    rows = long.groupBy("y", "i").agg(F.sum("w").alias("w"), F.sum(F.col("w") * v).alias("a"), F.sum(F.col("w") * v * v).alias("b")).collect()
    classes = sorted({r.y for r in rows})
    if classes != [0, 1]:
        raise ValueError("training pairs of both classes are needed")
    by = {y: sorted((r for r in rows if r.y == y), key=lambda r: r.i) for y in classes}
    total, out = sum(rs[0].w for rs in by.values()), {}
    if any(rs[0].w <= 0 for rs in by.values()):
        raise ValueError("a class of the training pairs has no weight")
    for y, rs in by.items():
        means = [r.a / r.w for r in rs]
        out[y] = (rs[0].w / total, means, [max(FLOOR, r.b / r.w - m * m) for r, m in zip(rs, means)])
    return out


def bayes_probability(model: dict, x: Column) -> Column:
    """Probability of class 1: the model is a handful of literals, no Python at work."""
    from math import log

    def side(y: int) -> Column:
        prior, means, variances = model[y]
        m = F.array(*[F.lit(float(v)) for v in means])
        s = F.array(*[F.lit(float(v)) for v in variances])
        each = F.zip_with(F.zip_with(x, m, lambda a, b: (a - b) * (a - b)), s, lambda d, v: F.log(v) + d / v)
        return F.lit(log(prior)) - 0.5 * F.aggregate(each, F.lit(0.0), lambda acc, v: acc + v)

    return 1 / (1 + F.exp(F.greatest(F.lit(-500.0), F.least(F.lit(500.0), side(0) - side(1)))))
