"""Connected components of an edge table by alternating large-star and small-star rounds.

Each round makes every node point at the least node that it sees; the graph shrinks to stars in O(log^2 n) rounds.
Rounds are joins and aggregations with map-side combine, each written once to the shared folder; the driver sees
two numbers a round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ertransfer.durable import release, settle


def _toward_least(edges: DataFrame, larger_only: bool) -> DataFrame:
    """One star step over rows (a, b) with a > b. Large star joins both directions, small star only towards smaller."""
    if larger_only:
        seen = edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = seen.groupBy("a").agg(F.min(F.least("a", "b")).alias("m"))
        return seen.join(least, "a").where("b > a and b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    hooked = edges.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return hooked.union(least.select("a", F.col("m").alias("b")))


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
    return row[0], row[1]


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Rows (node, component) for every node of ``edges`` (a, b); component is the least node reachable.

    Self loops, repeated edges and either direction are allowed; a row with a null end is ignored. An empty table
    gives an empty result. Raises if ``max_rounds`` rounds do not settle the graph.
    """
    now = settle(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    state = _state(now)
    for _ in range(max_rounds):
        if not state[0]:
            break
        large = _toward_least(now, True)
        after = settle(_toward_least(large.where("a > b").distinct(), False).distinct(), "edges")
        reached = _state(after)
        release(now)
        now = after
        if reached == state:
            break
        state = reached
    else:
        raise RuntimeError("the components did not settle")
    roots = now.select("b").distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).union(roots.select("b", "b"))
