"""Balance of classes and of datasets in training data. Draws are by hash: the same rows whatever the partitioning.

Rows carry a ``key`` that names them.
"""

from __future__ import annotations

from decimal import Decimal, localcontext

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ertransfer.durable import settle
from ertransfer.functions.portable import h32, unit


def _lowest(rows: DataFrame, n: int, seed: str) -> DataFrame:
    """The ``n`` rows of least hash: counts of its upper half lead to the last row wanted, and no row is moved."""
    if n <= 0:
        return rows.limit(0)
    drawn = rows.withColumn("_h", h32(f"{seed}:", F.col("key")))
    upper, left = F.shiftright("_h", 16), n
    for r in drawn.groupBy(upper.alias("u")).agg(F.count("*").alias("n")).orderBy("u").collect():  # at most 65,536 rows
        if r.n >= left:
            break
        left -= r.n
    else:
        return rows
    last = drawn.where(upper == r.u).select("_h", "key").orderBy("_h", "key").limit(left).collect()[-1]
    return drawn.where((F.col("_h") < last["_h"]) | ((F.col("_h") == last["_h"]) & (F.col("key") <= last["key"]))).drop("_h")


def undersample_sizes(matches: int, others: int, n: int, ratio: int = 3) -> tuple[int, int]:
    """How many matches and non-matches make up ``n`` rows at 1 to ``ratio``; too few matches are all taken."""
    m = min(matches, n // (ratio + 1))
    return m, min(others, n - m)


def undersample(rows: DataFrame, n: int, ratio: int = 3, seed: str = "u") -> DataFrame:
    """``n`` rows of (key, y, ...) with ``ratio`` non-matches for each match, as far as there are any."""
    counts = {r.y: r.n for r in rows.groupBy("y").agg(F.count("*").alias("n")).collect()}
    m, k = undersample_sizes(counts.get(1, 0), counts.get(0, 0), n, ratio)
    return _lowest(rows.where("y = 1"), m, seed).unionByName(_lowest(rows.where("y = 0"), k, seed))


def class_weights(rows: DataFrame) -> DataFrame:
    """``rows`` with w = m / (2 m_c), the weight of their class."""
    counts = rows.groupBy("y").agg(F.count("*").alias("_n"))
    total = counts.agg(F.sum("_n").alias("_m"))  # one row
    return rows.join(F.broadcast(counts.join(F.broadcast(total))), "y").withColumn("w", F.col("_m") / (2 * F.col("_n"))).drop("_n", "_m")


def dataset_weights(source: DataFrame, target: DataFrame) -> DataFrame:
    """Both tables with w: 1 for target rows, the ratio of target to source size for source rows (at most 1)."""
    ratio = min(1.0, target.count() / max(1, source.count()))
    return source.withColumn("w", F.lit(ratio)).unionByName(target.withColumn("w", F.lit(1.0)))


def replicate_random(target: DataFrame, size: int, seed: str = "r") -> DataFrame:
    """``size`` rows drawn from ``target`` with replacement; ``copy`` numbers the draws.

    The target is the small side; its rows are numbered by key.
    """
    n = target.count()
    if not n:
        return target.withColumn("copy", F.lit(0).cast("long"))
    at = target.withColumn("_at", (F.row_number().over(Window.orderBy("key")) - 1).cast("long"))
    drawn = target.sparkSession.range(size).select(F.col("id").alias("copy"), (h32(f"{seed}:", F.col("id")) % n).alias("_at"))
    return drawn.join(at, "_at").drop("_at")


def replicate_fixed(target: DataFrame, times: int) -> DataFrame:
    """Each row of ``target`` ``times`` times; ``copy`` numbers them."""
    return target.withColumn("copy", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(times - 1).cast("long"))))


def cap(source_size: int, target_size: int, ratio: int = 10) -> int:
    """The most source rows to train with."""
    return min(source_size, ratio * target_size)


def importance_sample(rows: DataFrame, k: int, seed: str = "i") -> DataFrame:
    """``k`` rows of (key, w, ...) drawn without replacement in proportion to w: exponential keys, the least win.

    Rows of weight 0 are never drawn. The sort keeps k rows a task.
    """
    wait = -F.log(unit(f"{seed}:", F.col("key"))) / F.col("w")
    return rows.where("w > 0").withColumn("_k", wait).orderBy("_k", "key").limit(k).drop("_k")


def importance_sample_with_replacement(rows: DataFrame, k: int, seed: str = "i") -> DataFrame:
    """``k`` draws in proportion to w with replacement: points of the running weight in the order of ``key``; ``copy`` numbers draws.

    Rows are dealt by ranges of the key. Each range sums its own weights from where the ranges before it end, and meets
    its own points in one ordered pass. Weights count in parts of the greatest one, in decimals, so that sums are exact
    whatever the ranges.
    """
    kept = rows.where("w > 0").select(F.col("key").cast("string").alias("key"), F.col("w").cast("double").alias("w"))
    greatest = kept.agg(F.max("w")).first()[0]
    if not greatest:
        return rows.limit(0).withColumn("copy", F.lit(0).cast("long"))
    exact = "decimal(38,15)"
    dealt = kept.repartitionByRange("key").select("key", (F.col("w") / greatest).cast("decimal(16,15)").alias("w"), F.spark_partition_id().alias("_part"))
    dealt = settle(dealt, "weights")
    ends, upto = [], Decimal(0)
    with localcontext() as context:
        context.prec = 60
        for r in dealt.groupBy("_part").agg(F.sum("w").alias("w")).orderBy("_part").collect():  # a row a range
            ends.append((r["_part"], upto, upto + r.w))
            upto += r.w
    spark = rows.sparkSession
    bounds = F.broadcast(spark.createDataFrame(ends, f"_part int, _from {exact}, _until {exact}"))
    order = Window.partitionBy("_part")
    run = dealt.join(bounds, "_part").select("_part", (F.col("_from") + F.sum("w").over(order.orderBy("key").rowsBetween(Window.unboundedPreceding, 0))).cast(exact).alias("_x"), F.lit(None).cast("long").alias("copy"), "key")
    at = F.least((unit(f"{seed}:", F.col("id")) * float(upto)).cast(exact), F.lit(upto).cast(exact))
    points = spark.range(k).select(F.col("id").alias("copy"), at.alias("_x"))
    # Zero, should the least point round to it, belongs to the first range.
    met = points.join(bounds, ((F.col("_x") > F.col("_from")) | ((F.col("_x") == 0) & (F.col("_from") == 0))) & (F.col("_x") <= F.col("_until")))
    both = met.select("_part", "_x", "copy", F.lit(None).cast("string").alias("key")).unionByName(run)
    # From the top down, the last row met is the first whose running weight reaches the point.
    down = order.orderBy(F.desc("_x"), F.col("copy").isNotNull(), F.desc("key")).rowsBetween(Window.unboundedPreceding, 0)
    hit = both.withColumn("_key", F.last("key", ignorenulls=True).over(down)).where("copy is not null").select("copy", F.col("_key").alias("key"))
    return hit.join(rows.withColumn("key", F.col("key").cast("string")), "key")


def top_weight(rows: DataFrame, k: int) -> DataFrame:
    """The ``k`` rows of greatest w: the fragile alternative to sampling."""
    return rows.orderBy(F.desc("w"), "key").limit(k)
