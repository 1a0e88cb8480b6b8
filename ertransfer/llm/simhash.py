"""SimHash near-duplicate groups by multi-index hashing.

A fingerprint is cut into two 32-bit segments. Two fingerprints at three or fewer differing bits differ in at most
one bit in one of the segments, so it is enough to look up, for each segment, the ball of radius one around its
value and to compare whole fingerprints inside the table entries found. Of two values that differ in one bit only
the one with the zero there asks, which halves the probes. Exact copies meet in one fingerprint before any of this.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ertransfer.durable import partitions_for, release, settle
from ertransfer.llm.batches import text_pieces
from ertransfer.llm.components import connected_components

SEED = 42
#: Buckets up to this size are compared pair by pair; larger ones are walked, giving a spanning forest only.
PAIRWISE = 16


def _bits_of(hashes: np.ndarray) -> int:
    """The fingerprint: bit i is set if over half of the hashes have it."""
    grid = np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    total = np.zeros(64, np.int64)
    for lo in range(0, len(grid), 255):  # sums of up to 255 ones fit a byte
        total += np.add.reduce(grid[lo : lo + 255], axis=0, dtype=np.uint8)
    return int(np.packbits(2 * total > len(grid), bitorder="little").view(np.uint64)[0])


def fingerprint(text: bytes, width: int) -> int:
    """Fingerprint of a UTF-8 text over lower-cased word shingles of ``width``; zero if it has no words."""
    words = text.lower().split()
    if not words:
        return 0
    if len(words) < width:
        shingles = [b" ".join(words)]
    else:
        shingles = map(b" ".join, zip(*(words[i:] for i in range(width))))
    return _bits_of(np.array([xxhash.xxh64_intdigest(s, SEED) for s in shingles], np.uint64))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3) -> DataFrame:
    """Rows (id, fp long) of all ``docs``, map-only. A null text is an empty one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(batches, "text"):
            fps = np.array([fingerprint(t, width) for t in piece.raw()], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([piece.rows.column("id"), pa.array(fps)], ["id", "fp"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "id long, fp long")


def _probes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    one = np.uint64(1)
    for batch in batches:
        fp = batch.column("fp").to_numpy().view(np.uint64)
        keys, owners = [], []
        for segment in (np.uint64(0), one):
            value = (fp >> (segment * np.uint64(32))) & np.uint64(0xFFFFFFFF)
            tag = segment << np.uint64(32)
            keys.append(value | tag)
            owners.append(fp)
            for i in range(32):
                bit = one << np.uint64(i)
                asks = (value & bit) == 0
                keys.append(value[asks] | bit | tag)
                owners.append(fp[asks])
        key, owner = np.concatenate(keys), np.concatenate(owners)
        for lo in range(0, len(key), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(key[lo : lo + 100_000].view(np.int64)), pa.array(owner[lo : lo + 100_000].view(np.int64))], ["key", "fp"])


def _near(x: np.ndarray, y: np.ndarray, bits: int) -> np.ndarray:
    return np.bitwise_count(x ^ y) <= bits


def _forest(fps: np.ndarray, bits: int) -> tuple[list, list]:
    """A spanning forest of the graph of near fingerprints among distinct ``fps``."""
    left, a, b = fps, [], []
    while left.size:
        queue, left = [left[0]], left[1:]
        while queue and left.size:
            x = queue.pop()
            near = _near(left, x, bits)
            if near.any():
                found = left[near]
                a.append(np.full(len(found), x, np.uint64))
                b.append(found)
                queue += list(found)
                left = left[~near]
    return a, b


def _links(bits: int):
    """Over rows (key, fp) sorted by key: links between near fingerprints that share a key."""

    def close(key: np.ndarray, fp: np.ndarray) -> pa.RecordBatch | None:
        edge = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1], [True]]))
        first, size = edge[:-1], np.diff(edge)
        a, b = [], []
        for n in np.unique(size[(size > 1) & (size <= PAIRWISE)]):
            block = fp[first[size == n][:, None] + np.arange(n)]
            i, j = np.triu_indices(int(n), 1)
            x, y = block[:, i].ravel(), block[:, j].ravel()
            ok = _near(x, y, bits)
            a.append(x[ok])
            b.append(y[ok])
        for at, n in zip(first[size > PAIRWISE], size[size > PAIRWISE]):
            x, y = _forest(np.unique(fp[at : at + n]), bits)
            a += x
            b += y
        if not a:
            return None
        x, y = np.concatenate(a), np.concatenate(b)
        keep = x != y
        pairs = np.unique(np.stack([np.maximum(x, y)[keep].view(np.int64), np.minimum(x, y)[keep].view(np.int64)]), axis=1)
        return pa.RecordBatch.from_arrays([pa.array(pairs[0]), pa.array(pairs[1])], ["a", "b"]) if pairs.size else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, fp = np.zeros(0, np.int64), np.zeros(0, np.uint64)
        for batch in batches:
            key = np.concatenate([key, batch.column("key").to_numpy()])
            fp = np.concatenate([fp, batch.column("fp").to_numpy().view(np.uint64)])
            cut = int(np.searchsorted(key, key[-1], "left"))  # the last key may go on in the next batch
            if cut:
                if (out := close(key[:cut], fp[:cut])) is not None:
                    yield out
                key, fp = key[cut:], fp[cut:]
        if len(key) and (out := close(key, fp)) is not None:
            yield out

    return run


def fingerprint_links(distinct: DataFrame, bits: int = 3) -> DataFrame:
    """Rows (a, b) that link the distinct fingerprints (fp) at ``bits`` or fewer differing bits.

    Every pair of small buckets, a spanning forest of large ones; a pair found in both segments comes twice.
    """
    if not 0 <= bits <= 3:
        raise ValueError("two segments with balls of radius one find links of 3 bits at most")
    n = partitions_for(distinct.sparkSession)
    keyed = distinct.select("fp").mapInArrow(_probes, "key long, fp long").repartition(n, "key").sortWithinPartitions("key")
    return keyed.mapInArrow(_links(bits), "a long, b long")


def near_duplicate_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, bits: int = 3) -> DataFrame:
    """Rows (id, fp, component): documents whose fingerprints are linked, directly or in steps, share a component.

    ``bits`` is the largest number of differing bits of a link, 3 at most with two segments. The component is the
    least id in it. Null ids group like others and never lead. Texts without words share fingerprint zero; repeated
    rows stay repeated; other columns of ``docs`` are ignored; an empty table gives no rows.
    """
    prints = settle(fingerprints(docs, id_col, text_col, width), "prints")
    first = settle(prints.groupBy("fp").agg(F.min("id").alias("first"), F.count("*").alias("n")), "fp")
    linked = connected_components(fingerprint_links(first, bits))
    members = linked.join(first, linked.node == first.fp).select("node", "component", "first")
    lead = members.groupBy("component").agg(F.min("first").alias("lead"))
    of_linked = members.join(lead, "component").select(F.col("node").alias("fp"), "lead")
    several = first.where("n > 1").join(of_linked, "fp", "left_anti").select("fp", F.col("first").alias("lead"))
    # A hot fingerprint makes one large join key; the join needs no co-location afterwards, so AQE may split it.
    return (
        prints.join(of_linked.union(several), "fp", "left")
        .select("id", "fp", F.coalesce("lead", "id").alias("component"))
    )


def fingerprint_hex(fp) -> F.Column:
    """16 lowercase hex digits of a fingerprint column."""
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
