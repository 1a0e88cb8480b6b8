"""Estimates of accuracy from a budget of labels, spent on strata of the classifier's score."""

from __future__ import annotations

from math import floor

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ertransfer.functions.portable import h32


def stratum(p: Column, strata: int = 5) -> Column:
    """Equal-width bins of the score, 1 in the last."""
    return F.least(F.floor(p * strata), F.lit(strata - 1)).cast("int")


def strata_table(scored: DataFrame, strata: int = 5) -> DataFrame:
    """Rows (stratum, size, v): v sums p (1 - p), the variance of the number of matches."""
    p = F.col("p")
    return scored.groupBy(stratum(p, strata).alias("stratum")).agg(F.count("*").alias("size"), F.sum(p * (1 - p)).alias("v"))


def shares(table: list[tuple[int, int, float]], how: str) -> dict[int, float]:
    """What part of the budget each stratum (number, size, v) is to get."""
    raw = {
        "equal": lambda size, v: 1.0,
        "proportional": lambda size, v: float(size),
        "variability": lambda size, v: v * size,
        "deviation": lambda size, v: (v / size) ** 0.5 * size,
    }[how]
    parts = {i: raw(size, v) for i, size, v in table}
    total = sum(parts.values())
    if not total:  # no stratum varies
        return shares(table, "proportional")
    return {i: x / total for i, x in parts.items()}


def allocate(table: list[tuple[int, int, float]], budget: int, how: str = "variability") -> dict[int, int]:
    """Labels for each stratum (number, size, v): whole numbers by largest remainder, none above its size.

    What a full stratum cannot take goes to the others in their proportions; a budget above all sizes takes everything.
    """
    open_ = {i: (i, size, v) for i, size, v in table}
    left = min(budget, sum(size for _, size, _ in table))
    out = {}
    while open_:
        part = shares(list(open_.values()), how)
        full = [i for i, (_, size, _) in open_.items() if left * part[i] > size]
        if not full:
            break
        for i in full:
            out[i] = open_.pop(i)[1]
        left -= sum(out[i] for i in full)
    if open_:
        quota = {i: left * part[i] for i in open_}
        whole = {i: floor(q + 1e-9) for i, q in quota.items()}
        order = sorted(open_, key=lambda i: (-(quota[i] - floor(quota[i])), i))
        more = set(order[: left - sum(whole.values())])
        out |= {i: n + (i in more) for i, n in whole.items()}
    return out


def draw(scored: DataFrame, budget: int, strata: int = 5, how: str = "variability", seed: str = "b") -> DataFrame:
    """The rows of ``scored`` (key, p) whose labels are to be bought: stratum and its size beside them.

    ``none`` draws from all rows alike. A threshold on the hash keeps all but a few times the draw from the sort.
    """
    rows = scored.withColumn("stratum", F.lit(0) if how == "none" else stratum(F.col("p"), strata)).withColumn("_h", h32(f"{seed}:", F.col("key")))
    p = F.col("p")
    table = [(r.stratum, r.n, r.v) for r in rows.groupBy("stratum").agg(F.count("*").alias("n"), F.sum(p * (1 - p)).alias("v")).collect()]  # a row for each stratum
    labels = allocate(sorted(table), budget, "proportional" if how == "none" else how)
    spark = scored.sparkSession
    least = lambda n, b: 1 << 32 if n <= 4 * b + 1000 else int((1 << 32) * min(1.0, (b + 6 * b**0.5 + 50) / n))
    plan = spark.createDataFrame([(i, n, labels[i], least(n, labels[i])) for i, n, _ in table], "stratum int, size long, labels int, _most long")
    near = rows.join(F.broadcast(plan), "stratum").where("_h < _most")
    place = F.row_number().over(Window.partitionBy("stratum").orderBy("_h", "key"))
    return near.withColumn("_at", place).where("_at <= labels").drop("_h", "_at", "_most", "labels")


def estimate(drawn: DataFrame, threshold: float = 0.5) -> DataFrame:
    """One row (labels, accuracy, recall, f, precision, pooled_recall, pooled_f) of drawn rows (stratum, size, p, y).

    Accuracy and recall of the strata are weighted by their sizes, f is their harmonic mean; strata without matches have
    no recall. The pooled figures weight every row by its stratum's size over its draw, as a control.
    """
    hit, y = F.col("p") >= threshold, F.col("y") == 1
    n = lambda c: F.count(F.when(c, 1)).cast("double")
    each = drawn.groupBy("stratum", "size").agg(F.count("*").alias("k"), n(hit == y).alias("right"), n(hit & y).alias("tp"), n(hit & ~y).alias("fp"), n(~hit & y).alias("fn"))
    size, k = F.col("size"), F.col("k")
    recall = F.try_divide(F.col("tp"), F.col("tp") + F.col("fn"))
    up = lambda c: F.sum(F.col(c) * size / k)
    t = each.agg(
        F.sum("k").alias("labels"), (F.sum(F.col("right") / k * size) / F.sum("size")).alias("accuracy"),
        F.coalesce(F.try_divide(F.sum(recall * size), F.sum(F.when(recall.isNotNull(), size))), F.lit(0.0)).alias("recall"),
        up("tp").alias("_tp"), up("fp").alias("_fp"), up("fn").alias("_fn"),
    )
    a, r = F.col("accuracy"), F.col("recall")
    zero = lambda c: F.coalesce(c, F.lit(0.0))
    return t.select(
        "labels", "accuracy", "recall", zero(F.try_divide(2 * a * r, a + r)).alias("f"),
        zero(F.try_divide(F.col("_tp"), F.col("_tp") + F.col("_fp"))).alias("precision"),
        zero(F.try_divide(F.col("_tp"), F.col("_tp") + F.col("_fn"))).alias("pooled_recall"),
        zero(F.try_divide(2 * F.col("_tp"), 2 * F.col("_tp") + F.col("_fp") + F.col("_fn"))).alias("pooled_f"),
    )
