"""Mixing sources to target weights by proportionate-fair scheduling.

A source of weight w owns blocks k = 0, 1, ... Block k is released at floor(k / w) and due at ceil((k + 1) / w);
earliest deadline first then keeps every source within one block of its share at every moment.

The schedule of a round repeats, as weights are whole numbers over their sum: one period has as many slots as the
weights add up to, is computed on the driver once (its length is a parameter, not a matter of the data) and serves as
a table of slots. A row's block follows from its place inside its source, its position from the slot of that block.
"""

from __future__ import annotations

import heapq
from fractions import Fraction
from math import gcd, lcm

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ertransfer.durable import partitions_for, settle

#: Slots of the longest period that is laid out.
LONGEST = 2_000_000


def exact(weight) -> Fraction:
    """The weight as it is written: 0.1 is a tenth."""
    return weight if isinstance(weight, Fraction) else Fraction(str(weight))


def whole_weights(weights: dict[str | None, float]) -> dict[str | None, int]:
    """Weights as the least whole numbers in exactly the same proportions; their sum is the period."""
    if not weights or min(weights.values()) <= 0:
        raise ValueError("weights must be positive")
    shares = {s: exact(w) for s, w in weights.items()}
    scale = lcm(*(x.denominator for x in shares.values()))
    whole = {s: int(x * scale) for s, x in shares.items()}
    common = gcd(*whole.values())
    if (period := sum(whole.values()) // common) > LONGEST:
        raise ValueError(f"these weights repeat only after {period} slots; give weights of fewer digits")
    return {s: w // common for s, w in whole.items()}


def schedule(whole: dict[str | None, int]) -> list[str | None]:
    """Which source owns each slot of one period."""
    period = sum(whole.values())
    names = sorted(whole, key=lambda s: (s is None, str(s)))
    waiting = [(0, -(-period // whole[s]), i, 0) for i, s in enumerate(names)]  # release, deadline, source, block
    heapq.heapify(waiting)
    ready: list[tuple[int, int, int]] = []
    out = []
    for slot in range(period):
        while waiting and waiting[0][0] <= slot:
            _, due, i, k = heapq.heappop(waiting)
            heapq.heappush(ready, (due, i, k))
        due, i, k = heapq.heappop(ready)
        w = whole[names[i]]
        out.append(names[i])
        if k + 1 < w:
            heapq.heappush(waiting, ((k + 1) * period // w, -(-(k + 2) * period // w), i, k + 1))
    return out


#: Bits below the partition in Spark's ascending row numbers.
ROW_BITS = 33


def _laid_out(rows: DataFrame, source: Column, order: list[Column]) -> DataFrame:
    """Rows (row struct, src, at, part), settled by source and order: ``at`` ascends with them, by one inside a part.

    Whole rows are dealt once, by ranges that split a hot source; their shuffle files go when they are settled.
    """
    keys = [f"o{i}" for i in range(len(order))]
    kept = rows.select(F.struct(*rows.columns).alias("row"), source.alias("src"), *[o.alias(k) for k, o in zip(keys, order, strict=True)])
    laid = kept.repartitionByRange(partitions_for(rows.sparkSession, 2), "src", *keys).sortWithinPartitions("src", *keys)
    laid = settle(laid.select("row", "src", F.monotonically_increasing_id().alias("at")), "mix", tidy=True)
    return laid.withColumn("part", F.shiftright("at", ROW_BITS))


def _runs(laid: DataFrame) -> list[tuple[str | None, int, int]]:
    """(src, part, shift) for each source in each part: ``at`` plus the shift is the row's place inside its source.

    A source's parts follow each other, so there are no more of these than sources and parts together.
    """
    counted = laid.groupBy("src", "part").agg(F.min("at").alias("first"), F.count("*").alias("n")).collect()
    before: dict[str | None, int] = {}
    out = []
    for r in sorted(counted, key=lambda r: r["part"]):
        out.append((r["src"], r["part"], before.get(r["src"], 0) - r["first"]))
        before[r["src"]] = before.get(r["src"], 0) + r["n"]
    return out


def mix(rows: DataFrame, weights: dict[str | None, float] | None = None, source_col: str = "source", order_cols: tuple[str, ...] = ("doc_id", "text"), block: int = 1) -> DataFrame:
    """Rows (row struct, src, place, block, position long): reading by position interleaves the sources by weight.

    ``weights`` names the share of each source (default: all equal); sources without a weight share the mean weight.
    No row is dropped: when a source runs out its slots stay empty, and positions leave those gaps. A null source is a
    source; repeated rows and ties of the order keep separate places; an empty table gives no rows.
    """
    spark = rows.sparkSession
    order = [F.col(c) if c != "text" else F.xxhash64(c) for c in order_cols]
    laid = _laid_out(rows, F.col(source_col).cast("string"), order)
    runs = _runs(laid)
    given = {s: exact(w) for s, w in (weights or {}).items()}
    mean = sum(given.values()) / len(given) if given else Fraction(1)
    shares = {s: given.get(s, mean) for s, _, _ in runs}
    if not shares:
        shares = {None: Fraction(1)}
    whole = whole_weights(shares)
    slots, seen = [], dict.fromkeys(whole, 0)
    for slot, s in enumerate(schedule(whole)):
        slots.append((s, seen[s], slot))
        seen[s] += 1
    spots = spark.createDataFrame(slots, "name string, turn long, slot long")  # a row for each slot
    shifts = spark.createDataFrame([(*r, whole[r[0]]) for r in runs], "name string, of_part long, shift long, per_period long")
    length = sum(whole.values())
    # Both tables are carried to the rows, which stay where they were settled.
    turned = laid.join(F.broadcast(shifts), F.col("src").eqNullSafe(F.col("name")) & (F.col("part") == F.col("of_part"))).drop("name")
    turned = turned.withColumn("place", F.col("at") + F.col("shift"))
    turned = turned.withColumn("block", F.floor(F.col("place") / F.lit(block))).withColumn("turn_of", F.col("block") % F.col("per_period"))
    joined = turned.join(F.broadcast(spots), F.col("src").eqNullSafe(F.col("name")) & (F.col("turn_of") == F.col("turn")))
    slot = F.floor(F.col("block") / F.col("per_period")) * length + F.col("slot")
    return joined.select("row", "src", "place", "block", (slot * block + F.col("place") % block).cast("long").alias("position"))
