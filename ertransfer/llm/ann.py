"""Approximate nearest neighbours on robust-pruned directed graphs, one a shard.

Vectors are dealt to shards by hash, so a hot key cannot fill one; each shard is a graph of bounded size. A shard is
built in one task: greedy beam searches over the growing graph propose neighbours, and relaxed pruning keeps an edge only if no kept neighbour is closer to its end by the factor
``alpha``. Every query searches every shard by beam, and the best of all shards are merged with exact distances.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Vectors of one shard; the number of shards grows with the table.
SHARD_ROWS = 4000
#: Queries that a task answers with one graph; beyond that the shard's graph is built again for the next block.
QUERY_BLOCK = 20_000
#: Queries that walk in step.
STEP = 2000


def _distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Squared distances of all rows of x to all of y, by the expanded form (for ranking only)."""
    return np.maximum((x * x).sum(1)[:, None] + (y * y).sum(1)[None] - 2 * x @ y.T, 0)


def robust_prune(at: int, candidates: np.ndarray, data: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """Out-edges of ``at``: nearest first, dropping candidates that a kept one is nearer to by ``alpha``."""
    near = _distances(data[at : at + 1], data[candidates])[0]
    order = np.argsort(near, kind="stable")
    candidates, near = candidates[order], near[order]
    between = _distances(data[candidates], data[candidates])
    alive, kept = np.ones(len(candidates), bool), []
    for i in range(len(candidates)):
        if alive[i]:
            kept.append(candidates[i])
            if len(kept) == degree:
                break
            alive &= alpha * alpha * between[i] > near
    return np.array(kept, np.int64)


def beam_search(queries: np.ndarray, data: np.ndarray, edges: np.ndarray, starts: np.ndarray, beam: int) -> np.ndarray:
    """For each query the ``beam`` nearest nodes met (-1 pads), walking all queries in step."""
    n = len(queries)
    rows = np.arange(n)[:, None]
    seen = np.zeros((n, len(data) + 1), bool)
    seen[:, -1] = True
    ids = np.tile(starts, (n, 1))
    seen[rows, ids] = True
    far = _distances(queries, data[starts])
    open_ = np.ones(ids.shape, bool)
    while open_.any():
        pick = np.where(open_, far, np.inf).argmin(1)
        active = open_[np.arange(n), pick]
        node = ids[np.arange(n), pick]
        open_[np.arange(n), pick] = False
        fresh = np.where(active[:, None], edges[node], len(data))
        fresh = np.where(seen[rows, fresh], len(data), fresh)
        seen[rows, fresh] = True
        vec = data[np.minimum(fresh, len(data) - 1)]
        d = ((vec - queries[:, None]) ** 2).sum(2)
        d[fresh == len(data)] = np.inf
        ids, far = np.concatenate([ids, fresh], 1), np.concatenate([far, d], 1)
        open_ = np.concatenate([open_, np.isfinite(d)], 1)
        if ids.shape[1] > beam:
            best = np.argpartition(far, beam - 1, axis=1)[:, :beam]
            ids, far, open_ = ids[rows, best], far[rows, best], open_[rows, best]
    return np.where(np.isfinite(far), ids, -1)


def build_graph(data: np.ndarray, degree: int = 32, alpha: float = 1.2, beam: int = 48, batch: int = 512, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """(edges padded with len(data), start nodes) of a graph over ``data``; nodes enter in batches of growing size."""
    n = len(data)
    edges = np.full((n, degree), n, np.int64)
    order = np.random.default_rng(seed).permutation(n)
    starts = order[: min(8, n)]
    lists: list[np.ndarray] = [np.zeros(0, np.int64)] * n
    for s in starts:
        lists[s] = robust_prune(s, starts[starts != s], data, degree, alpha) if n > 1 else lists[s]
        edges[s, : len(lists[s])] = lists[s]
    at = len(starts)
    while at < n:
        new = order[at : at + min(batch, at)]
        met = beam_search(data[new], data, edges, starts, min(beam, n))
        back: dict[int, list[int]] = {}
        for v, found in zip(new, met):
            found = found[(found >= 0) & (found != v)]
            lists[v] = robust_prune(v, found, data, degree, alpha)
            edges[v] = n
            edges[v, : len(lists[v])] = lists[v]
            for u in lists[v]:
                back.setdefault(int(u), []).append(int(v))
        for u, more in back.items():
            both = np.union1d(lists[u], np.array(more, np.int64))
            lists[u] = both if len(both) <= degree else robust_prune(u, both, data, degree, alpha)
            edges[u] = n
            edges[u, : len(lists[u])] = lists[u]
        at += len(new)
    return edges, starts


def usable(vector: str) -> F.Column:
    """True for vectors that can be searched: not null, empty or zero, all components present and finite."""
    v = F.col(vector)
    fine = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))
    return F.coalesce(v.isNotNull() & (F.size(v) > 0) & F.forall(v, fine) & F.exists(v, lambda x: x != 0), F.lit(False))


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 10, id_col: str = "vec_id", vec_col: str = "embedding", beam: int = 64, degree: int = 32, alpha: float = 1.2, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """Rows (query_id, rank int, vec_id, score double): the ``k`` nearest found for each of ``queries``.

    The beam holds at least 2 k + 8 nodes, so k rows are found wherever there are as many. A query never finds a row of
    its own id, and repeated rows of one id are one row if their vectors are equal; vectors may be of any length. Vectors of equal components are one node of the graph, so copies, however
    many, cost one place and all tie, smaller ids first. Vectors that :func:`usable` refuses and rows with a null id
    take no part; vectors of another length than the query's are not compared; empty tables give no rows.
    """
    spark = vectors.sparkSession
    beam = max(beam, 2 * k + 8)
    fine = lambda t: t.where(usable(vec_col)).where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v"))
    rows = fine(vectors).withColumn("key", F.xxhash64("v"))
    # Of each text of components only the k + 1 least ids can be among the nearest of a query.
    first = _least_ids(rows, k + 1)
    n = first.count()
    if not n:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    shards = max(1, -(-n // shard_rows))
    asked = fine(queries).distinct()
    blocks = max(1, -(-asked.count() // QUERY_BLOCK))
    dealt = first.select(F.pmod(F.xxhash64("key", F.lit(1)), F.lit(shards)).cast("int").alias("shard"), "v", "ids")
    # Each shard meets each block of queries: shards times queries rows, the stated query set against all rows.
    posed = asked.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1)))).withColumn("block", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    both = dealt.select("shard", "v", "ids", F.lit(None).cast("long").alias("id"), every.alias("block")).unionByName(
        posed.select("shard", "v", F.lit(None).cast("array<bigint>").alias("ids"), "id", "block")
    )

    def search(frame: pd.DataFrame) -> pd.DataFrame:
        out = []
        frame = frame.assign(dim=frame["v"].map(len))
        for _, same in frame.groupby("dim"):
            nodes, ask = same[same["id"].isna()], same[same["id"].notna()]
            if nodes.empty or ask.empty:
                continue
            data = np.stack(nodes["v"].to_numpy())
            edges, starts = build_graph(data, degree, alpha)
            owners = nodes["ids"].to_numpy()
            for lo in range(0, len(ask), STEP):
                part = ask.iloc[lo : lo + STEP]
                q = np.stack(part["v"].to_numpy())
                met = beam_search(q, data, edges, starts, min(beam, max(len(data), len(starts))))
                for qid, x, found in zip(part["id"].astype("int64"), q, met):
                    found = found[found >= 0]
                    score = np.sqrt(((data[found] - x) ** 2).sum(1))
                    pairs = [(s, int(i)) for s, f in zip(score.tolist(), found) for i in owners[f] if i != qid]
                    out += [(qid, i, s) for s, i in sorted(pairs)[:k]]
        return pd.DataFrame(out, columns=["query_id", "vec_id", "score"])

    hits = both.groupBy("shard", "block").applyInPandas(search, "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return hits.distinct().withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _least_ids(rows: DataFrame, most: int) -> DataFrame:
    """(key, v, ids): the least ``most`` ids of each vector, merged from pre-aggregated slices of hot ones."""
    sliced = rows.withColumn("slice", F.pmod(F.xxhash64("id"), F.lit(64)))
    some = sliced.groupBy("key", "v", "slice").agg(F.slice(F.array_sort(F.collect_set("id")), 1, most).alias("ids"))
    merged = some.groupBy("key", "v").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))).alias("ids"))
    return merged.select("key", "v", F.slice("ids", 1, most).alias("ids"))
