"""Substring dedup at the level of paragraphs: MinHash bands, exact Jaccard, connected components.

Equal paragraphs meet in one key first. Bands are tuned to the threshold and computed where the text lies; texts of
paragraphs travel only if a band met another paragraph, and then once for each distinct paragraph.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ertransfer.durable import release, settle
from ertransfer.llm.banding import WIDTH, BandRows, linked
from ertransfer.llm.batches import text_pieces
from ertransfer.llm.words import Words, shingles_of, words_of


def _lines(piece) -> tuple[Words, np.ndarray, np.ndarray, np.ndarray]:
    """(words, bounds, text number, line number) of the lines that hold a word; bounds are places among the words."""
    found = words_of(piece.data, piece.starts)
    ends = np.flatnonzero(piece.data == 10)
    line = np.searchsorted(ends, found.begin, "left")  # line breaks before each word, in the whole piece
    first = np.flatnonzero(np.r_[True, (line[1:] != line[:-1]) | (found.owner[1:] != found.owner[:-1])][: len(line)])
    owner = found.owner[first]
    return found, np.r_[first, len(line)], owner, line[first] - np.searchsorted(ends, piece.starts[owner], "left")


def _keys(found: Words, bounds: np.ndarray) -> list[bytes]:
    """128 bits for the word sequence of each line."""
    raw = found.lower.tobytes()
    begin, end = found.begin[bounds[:-1]].tolist(), found.end[bounds[1:] - 1].tolist()
    return [xxhash.xxh3_128_digest(b" ".join(raw[a:b].split())) for a, b in zip(begin, end)]


def paragraphs(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows (id, para, key binary): lines that hold a word; key hashes the lower-cased words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(batches, "text", 1 << 20):
            found, bounds, owner, line = _lines(piece)
            yield pa.RecordBatch.from_arrays([piece.rows.column("id").take(pa.array(owner)), pa.array(line.astype(np.int32)), pa.array(_keys(found, bounds), pa.binary())], ["id", "para", "key"])

    return _texts(docs, id_col, text_col).mapInArrow(run, "id long, para int, key binary")


def _texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))


def _bands(least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bands = BandRows(least)
        for piece in text_pieces(batches, "text", 1 << 20):
            found, bounds, *_ = _lines(piece)
            if len(bounds) > 1:
                yield from bands.rows(_keys(found, bounds), *shingles_of(found.value, bounds, WIDTH))

    return run


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Shingles of the lines that are asked for, from rows (text, wanted: lines of the text, null for all)."""
    for piece in text_pieces(batches, "text", 1 << 20):
        found, bounds, owner, line = _lines(piece)
        wanted = piece.rows.column("wanted").to_pylist()
        asked = [None if w is None else set(w) for w in wanted]
        pick = [k for k, (o, n) in enumerate(zip(owner.tolist(), line.tolist())) if asked[o] is None or n in asked[o]]
        keys = _keys(found, bounds)
        shingles, ends = shingles_of(found.value, bounds, WIDTH) if len(bounds) > 1 else (np.zeros(0, np.uint64), np.zeros(1, np.int64))
        sets = [np.unique(shingles[ends[k] : ends[k + 1]]).tobytes() for k in pick]
        yield pa.RecordBatch.from_arrays([pa.array([keys[k] for k in pick], pa.binary()), pa.array(sets, pa.binary())], ["key", "shingles"])


def repeated_paragraphs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = 0.8) -> DataFrame:
    """Rows (id, para, lead_id, lead_para, removed) of every paragraph that has a copy or a near copy.

    Paragraphs are lines with a word; links are a Jaccard similarity of ``least`` or more over shingles of five
    words, equal word sequences included. The least (id, para) of a component leads and stays, all others go. Null
    texts have no paragraphs; null ids sort first; repeated rows are copies that share (id, para), one of them a
    removed one only if its place is not the lead's; texts are read whole, and a very long one is held by one task;
    further columns are ignored; an empty table gives no rows.
    """
    texts = _texts(docs, id_col, text_col)
    found = settle(paragraphs(docs, id_col, text_col), "lines")

    def shingles(keys: DataFrame) -> DataFrame:
        # One place of each paragraph that met another; rows of one id may differ in text, so the key is checked below.
        place = found.where("id is not null").groupBy("key").agg(F.min(F.struct("id", "para")).alias("at"))
        nowhere = found.where("id is null").select("key").distinct()
        at = place.join(keys, "key", "left_semi").groupBy("at.id").agg(F.collect_set("at.para").alias("wanted"))
        some = texts.join(at, "id").select("text", "wanted").mapInArrow(_sets, "key binary, shingles binary")
        if not nowhere.isEmpty():  # texts without id are all read
            every = texts.where("id is null").select("text", F.lit(None).cast("array<int>").alias("wanted"))
            some = some.union(every.mapInArrow(_sets, "key binary, shingles binary"))
        return some.join(keys, "key", "left_semi").groupBy("key").agg(F.first("shingles").alias("shingles"))

    parts = linked(texts.mapInArrow(_bands(least), "band long, key binary"), shingles, least)
    of = found.join(parts.select(F.col("node").alias("key"), "component"), "key", "left").select("id", "para", F.coalesce("component", "key").alias("component"))
    of = settle(of, "classes")
    lead = of.groupBy("component").agg(F.min(F.struct("id", "para")).alias("lead"), F.count("*").alias("n")).where("n > 1")
    release(found, parts)
    return of.join(lead, "component").select(
        "id", "para", F.col("lead.id").alias("lead_id"), F.col("lead.para").alias("lead_para"),
        (~F.struct("id", "para").eqNullSafe(F.col("lead"))).alias("removed"),
    )
