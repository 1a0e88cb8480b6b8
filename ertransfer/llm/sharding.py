"""Minimax contiguous sharding in DataFrame operations only.

Groups of equal texts are atomic. They are laid out in order, and the shards are cut where the smallest feasible
capacity demands: the capacity is found by binary search, each trial filling shard after shard greedily.

No step holds all groups. One global sort gives every row its running size; group ends are the places where a cut may
fall. The driver sees the group ends only as cells (least, greatest end in a stretch of the running size), at most
``cells`` of them at a time. A greedy trial over cells has a cautious and a hopeful outcome; only the stretches where
the two differ are looked at again, in finer cells, until one capacity is left and its cuts are exact.
"""

from __future__ import annotations

from bisect import bisect_right
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ertransfer.durable import partitions_for, release, settle

CELLS = 20_000


def text_size(text: Column, overhead: int = 16) -> Column:
    """UTF-8 bytes of a text (null: none) plus a fixed overhead."""
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + overhead


@dataclass
class _Ends:
    """What is known of the group ends: for each cell its least and its greatest end, ascending."""

    low: list[int]
    high: list[int]

    def step(self, x: int, hopeful: bool) -> int:
        """The greatest end that is at most ``x``, or the outermost that it may be."""
        at = bisect_right(self.low, x) - 1
        if at < 0:
            return 0
        if x >= self.high[at]:
            return self.high[at]
        return x if hopeful else self.low[at]

    def path(self, capacity: int, shards: int, hopeful: bool) -> list[int]:
        """Where the shards end if each is filled to the capacity."""
        at, out = 0, []
        for _ in range(shards):
            at = self.step(at + capacity, hopeful)
            out.append(at)
        return out

    def least(self, low: int, high: int, shards: int, hopeful: bool) -> int:
        """The smallest capacity in [low, high] whose path reaches the last end."""
        while low < high:
            mid = (low + high) // 2
            if self.path(mid, shards, hopeful)[-1] >= self.high[-1]:
                high = mid
            else:
                low = mid + 1
        return low


def _cells(ends: DataFrame, width: int, where: Column | None) -> _Ends:
    picked = ends if where is None else ends.where(where)
    rows = picked.groupBy(F.floor(F.col("end") / F.lit(width)).alias("cell")).agg(F.min("end").alias("lo"), F.max("end").alias("hi")).collect()
    pairs = sorted((r.lo, r.hi) for r in rows)
    return _Ends([p[0] for p in pairs], [p[1] for p in pairs])


def _merged(known: _Ends, finer: _Ends) -> _Ends:
    """Cells of ``known`` with those that ``finer`` covers replaced."""
    pairs, starts = list(zip(finer.low, finer.high)), finer.low
    for lo, hi in zip(known.low, known.high):
        at = bisect_right(starts, hi) - 1
        if at < 0 or starts[at] < lo:
            pairs.append((lo, hi))
    pairs.sort()
    return _Ends([p[0] for p in pairs], [p[1] for p in pairs])


def minimax_cuts(ends: DataFrame, shards: int, largest: int, total: int, cells: int = CELLS) -> tuple[int, list[int]]:
    """The smallest feasible capacity and the ends of the shards, over group ends ``end`` (running sizes)."""
    width = max(1, -(-total // cells))
    known = _cells(ends, width, None)
    low, high = max(largest, -(-total // shards)), total
    while True:
        low = known.least(low, high, shards, True)
        high = known.least(low, high, shards, False)
        near, far = known.path(low, shards, False), known.path(high, shards, True)
        if low == high and near == known.path(low, shards, True):
            return low, near
        spans, before = [], (0, 0)
        for a, b in zip(near, far):  # a cut lies in [a, b]; the cells that touch the stretch are looked at again
            lo, hi = min(a, before[0] + low), min(max(b, before[1] + high), total)
            i, j = max(0, bisect_right(known.low, lo) - 1), bisect_right(known.low, hi) - 1
            spans.append((known.low[i], known.high[j]))
            before = (a, b)
        joined: list[list[int]] = []
        for lo, hi in sorted(spans):
            if joined and lo <= joined[-1][1]:
                joined[-1][1] = max(hi, joined[-1][1])
            else:
                joined.append([lo, hi])
        width = max(1, min(width // 2, sum(hi - lo + 1 for lo, hi in joined) // cells))
        where = F.lit(False)
        for lo, hi in joined:
            where = where | F.col("end").between(lo, hi)
        finer = _cells(ends, width, where)
        known = _merged(known, finer)


def minimax_shards(rows: DataFrame, shards: int, id_col: str = "doc_id", text_col: str = "text", order: list[str] | None = None, overhead: int = 16) -> DataFrame:
    """``rows`` with size, text_crc32, shard and slot: contiguous shards of whole groups, sizes as even as can be.

    A group is all rows of one text (null texts form one group); groups stand in the order of their first row by
    ``order`` (default: the id, then the text's hash), rows within a group in the same order. ``slot`` counts from
    zero without gaps inside each shard. A group larger than a fair share fills a shard of its own; with fewer groups
    than shards the last shards stay empty. Null ids sort first, repeated rows are separate members of their group,
    further columns pass through unless they bear a name of the output, and an empty table gives an empty result.
    """
    spark = rows.sparkSession
    text = F.col(text_col)
    names = {"size", "text_crc32", "shard", "slot"}
    by = [F.col(c) for c in order] if order else [F.col(id_col)]
    kept = [c for c in rows.columns if c != text_col and c not in names]
    base = rows.select(
        F.struct(*kept).alias("row"),
        F.struct(*by, F.xxhash64(text)).alias("rank"),
        text_size(text, overhead).alias("size"),
        F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("text_crc32"),
        F.sha2(text.cast("binary"), 256).alias("key"),
    )
    base = settle(base, "sizes")
    first = base.groupBy("key").agg(F.min("rank").alias("lead"), F.count("*").alias("n")).where("n > 1").drop("n")
    # Only texts with several copies need their group's first row; a hot one is one key of a plain join, which AQE splits.
    first = first.select(F.col("key").alias("shared"), "lead")
    parts = partitions_for(spark, 2)
    laid = (
        base.join(first, F.col("key").eqNullSafe(F.col("shared")), "left")
        .withColumn("lead", F.coalesce("lead", "rank"))
        .drop("shared", "key")
        .repartitionByRange(parts, "lead", "rank")
        .withColumn("part", F.spark_partition_id())
    )
    laid = settle(laid, "laid")
    release(base)
    totals = sorted((r.part, r.bytes, r.n, r.most) for r in laid.groupBy("part").agg(F.sum("size").alias("bytes"), F.count("*").alias("n"), F.max("size").alias("most")).collect())
    offsets, total, count = [], 0, 0
    for part, size, n, _ in totals:
        offsets.append((part, total, count))
        total, count = total + size, count + n
    start = F.broadcast(spark.createDataFrame(offsets, "part int, before long, rows_before long"))  # a row for each partition
    inside = Window.partitionBy("part").orderBy("lead", "rank", "text_crc32").rowsBetween(Window.unboundedPreceding, 0)
    ran = laid.join(start, "part").select(
        "row", "size", "text_crc32", "lead",
        (F.col("before") + F.sum("size").over(inside)).alias("end"),
        (F.col("rows_before") + F.row_number().over(inside) - 1).alias("at"),
    )
    ran = settle(ran, "ran")
    release(laid)
    out_of_group = ran.groupBy("lead").agg(F.max("end").alias("end"), F.sum("size").alias("bytes"))
    ends = settle(out_of_group, "ends")
    cuts: list[int] = []
    if total:
        largest = ends.agg(F.max("bytes")).first()[0]
        _, cuts = minimax_cuts(ends.select("end"), shards, largest, total)
    shard = sum((F.when(F.col("end") > cut, 1).otherwise(0) for cut in cuts[:-1]), F.lit(0)).cast("int")
    placed = ran.withColumn("shard", shard)
    heads = placed.groupBy("shard").agg(F.min("at").alias("head"))  # a row for each shard
    out = placed.join(F.broadcast(heads), "shard").select("row.*", "size", "text_crc32", "shard", (F.col("at") - F.col("head")).alias("slot"))
    release(ends)
    return out
