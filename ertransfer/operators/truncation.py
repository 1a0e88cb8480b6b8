"""The baseline without a common space: similarities of the attributes that both schemas share, and nothing else."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ertransfer.functions.vectors import MICRO


def truncated_pair_features(pairs: DataFrame, left: DataFrame, right: DataFrame, texts: list[str], equal: list[str], numbers: list[str]) -> DataFrame:
    """``pairs`` (dataset, id_l, id_r, y) with x: edit similarity of ``texts``, equality, closeness of ``numbers``, in millionths.

    Sides are rows (dataset, id, attributes...); a null on either side counts as unlike.
    """
    names = texts + equal + numbers
    side = lambda t, s: t.select("dataset", F.col("id").alias(f"id_{s}"), *[F.col(c).alias(f"{c}_{s}") for c in names])
    both = pairs.join(side(left, "l"), ["dataset", "id_l"]).join(side(right, "r"), ["dataset", "id_r"])
    like = []
    for c in names:
        a, b = F.col(f"{c}_l"), F.col(f"{c}_r")
        if c in texts:
            v = 1 - F.levenshtein(a, b) / F.greatest(F.length(a), F.length(b), F.lit(1))
        elif c in equal:
            v = (a == b).cast("double")
        else:
            v = 1 - F.least(F.lit(1.0), F.abs(a - b) / F.greatest(F.abs(a), F.abs(b), F.lit(1e-9)))
        like.append(F.coalesce(F.round(v * MICRO).cast("long"), F.lit(0).cast("long")))
    return both.select("dataset", "id_l", "id_r", "y", F.array(*like).alias("x"))
