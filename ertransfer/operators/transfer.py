"""Training strategies that reuse labelled pairs of related datasets, over rows (x array, y, w)."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ertransfer.functions.vectors import origin_weight, phi_source, phi_target, phi_unlabeled
from ertransfer.operators.classifiers import Fitted, fit

STRATEGIES = ("target_only", "source_only", "pooled", "weighted", "augmented", "semi")
#: Labels below this share of the available training data are limited.
LIMITED = 0.10
#: Weighted source rows must count as much as this many equal ones, else they are not weighted.
LEAST_SIZE = 10


def _as_list(sources) -> list[DataFrame]:
    return [sources] if isinstance(sources, DataFrame) else list(sources)


def _union(tables: Sequence[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, tables)


# --- which algorithm fits ----------------------------------------------------------------------------------------


def label_state(labels: Column | int | float, available: Column | int | float, limited: float = LIMITED) -> Column:
    """``none``, ``limited`` (under ``limited`` of the available training data) or ``adequate``."""
    n, of = (v if isinstance(v, Column) else F.lit(v) for v in (labels, available))
    return F.when(n == 0, "none").when(n < limited * of, "limited").otherwise("adequate")


def scenario(source: Column, target: Column, related: Column | None = None, pooled_adequate: Column | None = None) -> Column:
    """The training strategy for the label states of both sides.

    Adequate target labels need no transfer; without any, labelled source pairs are weighted; a limited target takes
    feature augmentation, or its semi-supervised form if the source is limited too, unless both together are adequate
    and related, when pooling them by augmentation will do.
    """
    together = F.lit(False) if pooled_adequate is None else pooled_adequate & (F.lit(True) if related is None else related)
    return (
        F.when(target == "adequate", "target_only")
        .when((source == "none") & (target == "none"), "no labels")
        .when(source == "none", "target_only")
        .when(target == "none", "weighted")
        .when(source == "adequate", "augmented")
        .when(together, "augmented")
        .otherwise("semi")
    )


def should_transfer(mean_mcc: Column, same_domain: Column | None = None, threshold: float = 0.2) -> Column:
    """``reuse``, ``reuse with care`` (another domain) or ``refuse``: sources that can be told from the target harm it."""
    other = F.lit(False) if same_domain is None else ~same_domain
    return F.when(mean_mcc > threshold, "refuse").when(other, "reuse with care").otherwise("reuse")


# --- instance weights --------------------------------------------------------------------------------------------


def origin_rows(sources, target: DataFrame) -> DataFrame:
    """Rows (x, y, w): 1 for a pair of any source, 0 for one of the target, labels set aside."""
    rows = lambda t, y: t.select("x", F.lit(y).alias("y"), F.lit(1.0).alias("w"))
    return _union([rows(s, 1) for s in _as_list(sources)] + [rows(target, 0)])


def origin_weights(source: DataFrame, target: DataFrame, clip: float | None = None, kind: str = "gnb", fitted: Fitted | None = None, prior_correct: bool = False) -> DataFrame:
    """``source`` with p_origin, the probability of stemming from a source, and w = 1 / p - 1 (clipped if asked).

    ``prior_correct`` multiplies by the ratio of the two sizes, which makes w a ratio of densities.
    """
    model = fitted or fit(kind, origin_rows(source, target))
    ratio = source.count() / max(1, target.count()) if prior_correct else 1.0
    scored = model.score(source.drop("p_origin"), "x", "p_origin")
    return scored.withColumn("w", origin_weight(F.greatest(F.col("p_origin"), F.lit(1e-12))) * ratio if not clip else F.least(origin_weight(F.greatest(F.col("p_origin"), F.lit(1e-12))) * ratio, F.lit(float(clip))))


def effective_size(weighted: DataFrame) -> DataFrame:
    """One row (n, ess): the rows and the (sum of weights) squared over the sum of squares, 0 without weight."""
    w = F.col("w")
    return weighted.agg(F.count("*").alias("n"), F.coalesce(F.try_divide(F.sum(w) * F.sum(w), F.sum(w * w)), F.lit(0.0)).alias("ess"))


def kernel_mean_weights(source, target, width: float = 1.0, bound: float = 20.0, steps: int = 300):
    """Weights of rows of ``source`` (numpy) that bring its kernel mean to that of ``target``, by projected descent.

    For samples of a few thousand rows at most: the kernel matrix grows with the square.
    """
    import numpy as np

    if len(source) > 4000 or len(target) > 4000:
        raise ValueError("kernel mean matching takes samples of at most 4,000 rows")
    gram = lambda a, b: np.exp(-((a[:, None] - b[None]) ** 2).sum(2) / (2 * width * width))
    k, kappa = gram(source, source), gram(source, target).mean(1) * len(source)
    w, rate = np.ones(len(source)), 1 / max(1e-9, np.abs(k).sum(1).max())
    for _ in range(steps):
        w = np.clip(w - rate * (k @ w - kappa), 0, bound)
    return w


# --- strategies --------------------------------------------------------------------------------------------------


def training_table(strategy: str, sources, labelled: DataFrame, unlabelled: DataFrame, width: int, clip: float | None = None, origin: str = "gnb", tie: str = "last") -> tuple[DataFrame, int]:
    """(training rows x, y, w, their width) of a strategy for one source or a list of them.

    Where the weights leave too few effective rows, the source is used unweighted.

    ``tie`` says which source's block an unlabelled pair opposes to the target's: the ``last`` one's, or in one copy
    ``each``.
    """
    sources = _as_list(sources)
    n = len(sources)
    x, one = F.col("x"), F.lit(1.0).alias("w")
    plain = lambda t: t.select("x", "y", one)
    if strategy == "target_only":
        return plain(labelled), width
    if strategy == "source_only":
        return _union([plain(s) for s in sources]), width
    if strategy == "pooled":
        return _union([plain(t) for t in [*sources, labelled]]), width
    if strategy == "weighted":
        model = fit(origin, origin_rows(sources, unlabelled))
        rows = _union([origin_weights(s, unlabelled, clip, fitted=model).select("x", "y", "w") for s in sources])
        if effective_size(rows).first().ess < LEAST_SIZE:  # a handful of rows would decide: as good as no source
            rows = rows.withColumn("w", F.lit(1.0))
        return rows, width
    rows = [s.select(phi_source(x, width, i, n).alias("x"), "y", one) for i, s in enumerate(sources, 1)]
    rows.append(labelled.select(phi_target(x, width, n).alias("x"), "y", one))
    if strategy == "semi":
        opposed = [n] if tie == "last" else range(1, n + 1)
        rows += [unlabelled.select(phi_unlabeled(x, width, n, i).alias("x"), F.explode(F.array(F.lit(0), F.lit(1))).alias("y"), one) for i in opposed]
    elif strategy != "augmented":
        raise ValueError(f"strategy {strategy} is none of {', '.join(STRATEGIES)}")
    return _union(rows), (n + 2) * width


def apply_strategy(strategy: str, sources, labelled: DataFrame, unlabelled: DataFrame, test: DataFrame, width: int, kind: str = "gnb", **options) -> DataFrame:
    """``test`` with p, the probability of a match, after training ``kind`` by ``strategy``.

    To train for the source instead of the target, give the two the other way round.
    """
    if strategy == "target_only" and labelled.isEmpty():
        raise ValueError("without labelled target pairs nothing can be learnt from the target alone")
    train, wide = training_table(strategy, sources, labelled, unlabelled, width, **options)
    n = wide // width - 2
    x = phi_target(F.col("x"), width, n) if wide > width else F.col("x")
    return fit(kind, train).score(test.withColumn("z", x), "z").drop("z")
