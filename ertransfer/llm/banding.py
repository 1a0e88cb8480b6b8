"""Links between texts of like shingles: tuned MinHash bands, exact Jaccard, connected components.

Bands are tuned to the wanted similarity: as few rows a band as keep chance meetings rare, and as many bands as find a
pair at the threshold with the wanted chance. A map task sends one thin row (band, key) for each band of a distinct text; sorted
by band, only those that meet another key are kept. Bands of the same members are walked once, with the shingles of
members that met at all: each member finds its exact neighbours, giving a spanning forest of the links, never all pairs.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from math import ceil, log

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ertransfer.durable import partitions_for, release, settle
from ertransfer.llm.components import connected_components
from ertransfer.llm.words import mix

WIDTH = 5
#: Chance that a pair at the least similarity meets in a band.
RECALL = 0.9999
_SALTS = np.random.default_rng(11).integers(0, 1 << 64, (2, 1024), dtype=np.uint64)


def tuned(least: float, recall: float = RECALL, rows: int = 4) -> tuple[int, int]:
    """(bands, rows): ``rows``, fewer for low thresholds, and the bands that give a pair at ``least`` the wanted chance."""
    while rows > 1 and least**rows < 0.2:
        rows -= 1
    return ceil(log(1 - recall) / log(1 - min(1 - 1e-9, least**rows))), rows


def bands_of(shingles: np.ndarray, bounds: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """(texts, bands): a hash for each band of each group of shingles; repeated shingles do not matter."""
    out = np.empty((len(bounds) - 1, bands), np.uint64)
    for b in range(bands):
        whole = np.full(len(bounds) - 1, np.uint64(b + 1))
        for j in range(b * rows, (b + 1) * rows):
            least = np.minimum.reduceat((shingles ^ _SALTS[0, j]) * (_SALTS[1, j] | np.uint64(1)), bounds[:-1])
            whole = whole * np.uint64(0x9E3779B97F4A7C15) + least
        out[:, b] = mix(whole)
    return out


def distinct_sets(shingles: np.ndarray, bounds: np.ndarray) -> list[np.ndarray]:
    """The sorted distinct shingles of each group."""
    return [np.unique(shingles[a:b]) for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist())]


class BandRows:
    """Rows (band, key) of the texts of one task, each key once for as many keys as the task remembers."""

    def __init__(self, least: float, remembered: int = 400_000):
        self.tuned, self.remembered, self.seen = tuned(least), remembered, set()

    def rows(self, keys: list[bytes], shingles: np.ndarray, bounds: np.ndarray) -> Iterator[pa.RecordBatch]:
        first = {k: i for i, k in reversed(list(enumerate(keys))) if k not in self.seen}
        if not first:
            return
        if len(self.seen) > self.remembered:
            self.seen.clear()
        self.seen.update(first)
        at = np.fromiter(first.values(), np.int64, len(first))
        bands = bands_of(shingles, bounds, *self.tuned)[at]
        where = pa.array(np.repeat(np.arange(len(at)), bands.shape[1]))
        yield pa.RecordBatch.from_arrays([pa.array(bands.reshape(-1).view(np.int64)), pa.array(list(first), pa.binary()).take(where)], ["band", "key"])


def _walk(keys: list[bytes], sets: list[np.ndarray], least: float) -> list[tuple[bytes, bytes]]:
    """Spanning forest of the pairs at ``least`` Jaccard or more; each member is compared with those not yet reached."""
    sizes = np.array([len(s) for s in sets])
    flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
    left = np.ones(len(sets), bool)
    edges = []
    for root in range(len(sets)):
        if not left[root]:
            continue
        left[root] = False
        queue = [root]
        while queue:
            live = left[owner]
            flat, owner = flat[live], owner[live]
            if not len(flat):
                return edges
            i = queue.pop()
            at = np.minimum(np.searchsorted(sets[i], flat), sizes[i] - 1)
            both = np.bincount(owner[sets[i][at] == flat], minlength=len(sets))
            near = np.flatnonzero(left & (both >= least * (sizes + sizes[i] - both)))
            left[near] = False
            queue += near.tolist()
            edges += [(keys[i], keys[j]) for j in near.tolist()]
    return edges


def _links(least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, keys, sets, edges = None, [], [], []

        def out():
            return pa.RecordBatch.from_arrays([pa.array([e[0] for e in edges], pa.binary()), pa.array([e[1] for e in edges], pa.binary())], ["a", "b"])

        for batch in batches:
            for band, key, raw in zip(*(batch.column(c).to_pylist() for c in ("band", "key", "shingles"))):
                if band != now:
                    if len(keys) > 1:
                        edges += _walk(keys, sets, least)
                        if len(edges) > 10_000:
                            yield out()
                            edges = []
                    now, keys, sets = band, [], []
                keys.append(key)
                sets.append(np.frombuffer(raw, np.uint64))
        if len(keys) > 1:
            edges += _walk(keys, sets, least)
        yield out()

    return run


def linked(banded: DataFrame, shingles_of_keys: Callable[[DataFrame], DataFrame], least: float) -> DataFrame:
    """Rows (node, component) for keys linked to another key, from rows (band, key) with repeats.

    ``shingles_of_keys`` turns rows (key), those that met another, into rows (key, shingles: sorted distinct 64-bit
    hashes as bytes). The component is the least key in it. Members of one band are walked in one task.
    """
    n = partitions_for(banded.sparkSession)
    # Tasks send a key once, however many copies they read; the window only looks at neighbours, nothing is gathered.
    order = Window.partitionBy("band").orderBy("key")
    beside = banded.select("band", "key", F.lag("key").over(order).alias("before"), F.lead("key").over(order).alias("after"))
    met = settle(beside.where("before <> key or after <> key").select("band", "key").distinct(), "met")
    groups = met.groupBy("band").agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("key")).alias("who"))
    groups = groups.groupBy("n", "who").agg(F.min("band").alias("band")).select("band")
    sets = settle(shingles_of_keys(met.select("key").distinct()), "shingles")
    members = met.join(groups, "band").join(sets, "key").select("band", "key", "shingles").repartition(n, "band").sortWithinPartitions("band")
    edges = settle(members.mapInArrow(_links(least), "a binary, b binary"), "links")
    release(met, sets)
    parts = connected_components(edges)
    release(edges)
    return parts
