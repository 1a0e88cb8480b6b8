"""Groups of near copies among whole texts: candidates, exact Jaccard over word shingles, connected components.

Candidates come from SimHash fingerprints by multi-index hashing, and from MinHash bands: at a Jaccard similarity of
0.8 about 10 of 64 bits differ, which small Hamming balls cannot reach. Texts of linked fingerprints meet in one more
band; every candidate is verified exactly, whichever way it was found.

Only texts that share a band with another one are shingled again and brought together; every band is walked whole, so
a pair at the threshold is lost only if none of the bands agrees (a chance below 1e-4 at the threshold).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ertransfer.durable import release, settle
from ertransfer.llm.banding import WIDTH, BandRows, distinct_sets, linked
from ertransfer.llm.batches import text_pieces
from ertransfer.llm.simhash import fingerprint_links, fingerprints
from ertransfer.llm.words import shingles_of, words_of


def text_key(text: Column) -> Column:
    """128 bits for a text; a null text is an empty one."""
    return F.unhex(F.md5(F.coalesce(text, F.lit("")).cast("binary")))


def _shingled(piece) -> tuple[np.ndarray, np.ndarray]:
    """Shingles of each text of a piece; a text without words has a shingle of its own kind."""
    found = words_of(piece.data, piece.starts)
    counts = np.bincount(found.owner, minlength=len(piece.starts) - 1)
    empty = counts == 0
    # A text without words is given one word that no text can hold.
    bounds = np.r_[0, np.cumsum(np.maximum(1, counts))]
    value = np.full(bounds[-1], np.uint64(0x0123456789ABCDEF))
    place = np.arange(len(found.owner)) + np.cumsum(empty)[found.owner]
    value[place] = found.value
    return shingles_of(value, bounds, WIDTH)


def _bands(least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bands = BandRows(least)
        for piece in text_pieces(batches, "text", 1 << 20):
            yield from bands.rows(piece.rows.column("key").to_pylist(), *_shingled(piece))

    return run


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for piece in text_pieces(batches, "text", 1 << 20):
        sets = distinct_sets(*_shingled(piece))
        yield pa.RecordBatch.from_arrays([piece.rows.column("key"), pa.array([s.tobytes() for s in sets], pa.binary())], ["key", "shingles"])


def _fingerprint_bands(texts: DataFrame) -> tuple[DataFrame, list[DataFrame]]:
    """Rows (band, key): texts of one fingerprint share a band, and so do those of two linked ones; what to release.

    A band holds distinct texts a few bits apart, never a chain of links. Keys travel as 64 bits: two that agree there
    only meet in vain.
    """
    named = texts.select("key", F.xxhash64("key").alias("id"), "text")
    prints = settle(fingerprints(named, "id", "text", WIDTH).distinct(), "prints")
    links = settle(fingerprint_links(prints.select("fp").distinct()).distinct(), "near")
    pair = F.xxhash64(F.lit("pair"), "a", "b").alias("band")
    ends = links.select(pair, F.col("a").alias("fp")).union(links.select(pair, F.col("b").alias("fp")))
    bands = prints.select(F.xxhash64(F.lit("same"), "fp").alias("band"), "id").union(ends.join(prints, "fp").select("band", "id"))
    return bands.join(named.select("id", "key").distinct(), "id").select("band", "key"), [prints, links]


def near_copies(texts: DataFrame, least: float = 0.8) -> DataFrame:
    """Rows (node, component) for the keys of ``texts`` (key, text) that are linked to another key.

    Links are a Jaccard similarity of ``least`` or more over the distinct shingles of five lower-cased words; a text of
    fewer words is one shingle. The component is the least key in it.
    """

    def shingles(keys: DataFrame) -> DataFrame:
        # The map between join and aggregation lets AQE split the join where one text has very many copies.
        asked = texts.join(keys, "key", "left_semi").select("key", "text")
        return asked.mapInArrow(_sets, "key binary, shingles binary").groupBy("key").agg(F.first("shingles").alias("shingles"))

    alike, settled = _fingerprint_bands(texts)
    groups = linked(texts.mapInArrow(_bands(least), "band long, key binary").union(alike), shingles, least)
    release(*settled)
    return groups
