"""Repeated passages inside paragraphs: windows of words picked by their hashes alone, wherever lines break.

Of every run of WINDOWS neighbouring windows of WIDTH words the one of least hash is picked, so two texts that share
WIDTH + WINDOWS - 1 = 50 words in a row pick the same window inside them. Windows ignore line breaks. Two windows are
the same if 128 bits of hash are.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ertransfer.durable import settle
from ertransfer.llm.batches import text_pieces
from ertransfer.llm.words import run_hashes, window_least, words_of

WIDTH, WINDOWS = 25, 26


def _picked(piece) -> tuple[np.ndarray, ...]:
    """(text number, line, word, two 64-bit hashes) of the windows picked; none in texts of under 50 words."""
    found = words_of(piece.data, piece.starts)
    first = np.searchsorted(found.owner, np.arange(len(piece.starts)), "left")  # of each text, among the words
    one, two = run_hashes(found.value, WIDTH), run_hashes(found.value, WIDTH, 1)
    if len(one) < WINDOWS:
        return (np.zeros(0, np.int64),) * 3 + (one[:0], two[:0])
    at = window_least(one, WINDOWS)
    whole = found.owner[: len(at)] == found.owner[WIDTH + WINDOWS - 2 :]  # the run of 50 words lies in one text
    at = np.unique(at[whole])
    owner = found.owner[at]
    ends = np.flatnonzero(piece.data == 10)
    line = np.searchsorted(ends, found.begin[at], "left") - np.searchsorted(ends, piece.starts[owner], "left")
    return owner, line, at - first[owner], one[at], two[at]


def windows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows (id, para, word, k1, k2): the windows picked, with the line and the word of the text where each begins."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(batches, "text", 1 << 20):
            owner, line, word, one, two = _picked(piece)
            yield pa.RecordBatch.from_arrays(
                [piece.rows.column("id").take(pa.array(owner)), pa.array(line.astype(np.int32)), pa.array(word), pa.array(one.view(np.int64)), pa.array(two.view(np.int64))],
                ["id", "para", "word", "k1", "k2"],
            )

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "id long, para int, word long, k1 long, k2 long")


def repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (id, para, word, n_words, lead_id, lead_para, lead_word, removed) of every picked window that has a copy.

    The least (id, para, word) leads and stays. Null texts have no windows; null ids sort first.
    """
    found = settle(windows(docs, id_col, text_col), "windows")
    place = F.struct("id", "para", "word")
    lead = found.groupBy("k1", "k2").agg(F.min(place).alias("lead"), F.count("*").alias("n")).where("n > 1")
    # A hot passage makes one large join key; nothing after the join needs co-location, so AQE may split it.
    return found.join(lead, ["k1", "k2"]).select(
        "id", "para", "word", F.lit(WIDTH).alias("n_words"), F.col("lead.id").alias("lead_id"), F.col("lead.para").alias("lead_para"),
        F.col("lead.word").alias("lead_word"), (~place.eqNullSafe(F.col("lead"))).alias("removed"),
    )
