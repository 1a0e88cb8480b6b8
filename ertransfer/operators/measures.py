"""Accuracy and shift measures, as aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def _f(tp: Column, fp: Column, fn: Column) -> Column:
    return F.coalesce(F.try_divide(2.0 * tp, 2.0 * tp + fp + fn), F.lit(0.0))


def decide(scored: DataFrame, threshold: float = 0.5) -> DataFrame:
    """``scored`` with prediction 1 where p reaches the threshold."""
    return scored.withColumn("prediction", (F.col("p") >= threshold).cast("int"))


def measures(scored: DataFrame, threshold: float = 0.5, by: tuple[str, ...] = ()) -> DataFrame:
    """Rows tp, fp, fn, tn, precision, recall, f of scored pairs (p, y), one for each value of ``by``; 0 for 0 / 0."""
    hit, y = F.col("p") >= threshold, F.col("y") == 1
    n = lambda c: F.count(F.when(c, 1))
    t = scored.groupBy(*by).agg(n(hit & y).alias("tp"), n(hit & ~y).alias("fp"), n(~hit & y).alias("fn"), n(~hit & ~y).alias("tn"))
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    share = lambda a, b: F.coalesce(F.try_divide(a.cast("double"), b), F.lit(0.0))
    return t.withColumns({"precision": share(tp, tp + fp), "recall": share(tp, tp + fn), "f": _f(tp, fp, fn)})


def matthews(confusion: DataFrame) -> DataFrame:
    """``confusion`` with mcc (0 where a margin is empty) and d_A from its accuracy."""
    tp, fp, fn, tn = (F.col(c).cast("double") for c in ("tp", "fp", "fn", "tn"))
    under = F.sqrt((tp + fp) * (tp + fn) * (tn + fp) * (tn + fn))
    d_a = F.coalesce(2 * (F.try_divide(tp + tn, tp + tn + fp + fn) - 0.5), F.lit(0.0))
    return confusion.withColumn("mcc", F.coalesce(F.try_divide(tp * tn - fp * fn, under), F.lit(0.0))).withColumn("d_a", d_a)


def improvement(results: DataFrame, baselines: list[str]) -> DataFrame:
    """Rows (key columns, algorithm, f, best, delta): F of each algorithm minus the best of the ``baselines``.

    ``results`` are rows (task, classifier, size, algorithm, f).
    """
    key = ["task", "classifier", "size"]
    best = results.where(F.col("algorithm").isin(baselines)).groupBy(*key).agg(F.max("f").alias("best"))
    return results.join(best, key).select(*key, "algorithm", "f", "best", (F.col("f") - F.col("best")).alias("delta"))


def histogram(pairs: DataFrame, value: str = "cosine", bins: int = 20, by: tuple[str, ...] = ("dataset",)) -> DataFrame:
    """Rows (by, bin, matches, non_matches, overlap): values from 0 to 1 in equal bins, 1 in the last.

    ``overlap`` is the lesser of the two classes' shares in the bin; its sum says how far the classes cover each other.
    """
    bin_ = F.least(F.greatest(F.floor(F.col(value) * bins), F.lit(0)), F.lit(bins - 1)).cast("int")
    n = lambda c: F.count(F.when(c, 1))
    counts = pairs.groupBy(*by, bin_.alias("bin")).agg(n(F.col("y") == 1).alias("matches"), n(F.col("y") == 0).alias("non_matches"))
    whole = Window.partitionBy(*by)
    share = lambda c: F.coalesce(F.try_divide(F.col(c).cast("double"), F.sum(c).over(whole)), F.lit(0.0))
    return counts.withColumn("overlap", F.least(share("matches"), share("non_matches")))


def monotonicity(pairs: DataFrame, value: str, bins: int = 10, by: tuple[str, ...] = ()) -> DataFrame:
    """Rows (by, bin, n, rate, inversion): the share of matches in each bin, and whether it falls below the bin before."""
    bin_ = F.least(F.greatest(F.floor(F.col(value) * bins), F.lit(0)), F.lit(bins - 1)).cast("int")
    rates = pairs.groupBy(*by, bin_.alias("bin")).agg(F.count("*").alias("n"), F.avg(F.col("y").cast("double")).alias("rate"))
    before = F.lag("rate").over(Window.partitionBy(*(by or [F.lit(0)])).orderBy("bin"))  # a row for each bin
    return rates.withColumn("inversion", F.coalesce(F.col("rate") < before, F.lit(False)))


def class_ratio(pairs: DataFrame, by: str = "dataset") -> DataFrame:
    """Rows (by, n, matches, prior, ratio): class ratio of non-matches to matches."""
    m = F.sum(F.col("y"))
    return pairs.groupBy(by).agg(F.count("*").alias("n"), m.alias("matches"), F.avg(F.col("y").cast("double")).alias("prior"), F.try_divide(F.count("*") - m, m).alias("ratio"))


def vote(predictions: DataFrame, rule: str = "majority") -> DataFrame:
    """Rows (key, votes, models, prediction) of rows (key, model, prediction 0/1): labels completed by several models.

    ``majority`` asks for more than half of the votes, ``all`` for each, ``any`` for one.
    """
    t = predictions.groupBy("key").agg(F.sum("prediction").alias("votes"), F.count("*").alias("models"))
    rules = {"majority": F.col("votes") * 2 > F.col("models"), "all": F.col("votes") == F.col("models"), "any": F.col("votes") > 0}
    return t.withColumn("prediction", rules[rule].cast("int"))


def ranking_agreement(ranks: DataFrame) -> DataFrame:
    """One row (pairs, inversions) of rows (source, predicted, measured): pairs of sources that the two orders swap."""
    a, b = ranks.alias("a"), ranks.alias("b")
    swapped = (F.col("a.predicted") - F.col("b.predicted")) * (F.col("a.measured") - F.col("b.measured")) < 0
    both = a.join(b, F.col("a.source") < F.col("b.source"))  # a row for each source
    return both.agg(F.count("*").alias("pairs"), F.count(F.when(swapped, 1)).alias("inversions"))
