"""Benchmark decontamination by multi-pattern search over words, with block shifts.

Test windows are the patterns and words are the alphabet. A table over pairs of words says how far a search may jump
when that pair stands at the end of the current window; only where it may not jump does the bucket of that pair name
the windows that end so, which are then compared word by word.

The windows are dealt into blocks of a bounded size, each sent to the executors once. A block is a map-only pass that
adds its hits to the row, so documents are neither shuffled nor collected, however many blocks the benchmark fills.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ertransfer.durable import release, settle
from ertransfer.llm.batches import text_pieces

WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
WINDOW = 10
#: Bytes of window text in one block.
BLOCK_BYTES = 32 << 20


def words_of(text: bytes) -> list[bytes]:
    return WORD.findall(text.lower())


class ShiftSearch:
    """Search for word tuples of one length: shifts by the last words of a window, buckets where the shift is zero."""

    def __init__(self, patterns: dict[tuple[bytes, ...], list[int]], length: int):
        self.length, self.block = length, min(2, length)
        self.shift: dict[tuple[bytes, ...], int] = {}
        self.buckets: dict[tuple[bytes, ...], dict] = defaultdict(dict)
        for words, owners in patterns.items():
            for end in range(self.block, length + 1):
                key, jump = words[end - self.block : end], length - end
                self.shift[key] = min(jump, self.shift.get(key, length))
            self.buckets[words[length - self.block :]][words] = owners

    def find(self, words: list[bytes]) -> Iterator[tuple[int, list[int]]]:
        """(start, owners) of every occurrence."""
        length, block, shift, buckets = self.length, self.block, self.shift, self.buckets
        beyond, end, n = length - block + 1, length, len(words)
        while end <= n:
            key = tuple(words[end - block : end])
            jump = shift.get(key, beyond)
            if not jump:
                owners = buckets[key].get(tuple(words[end - length : end]))
                if owners:
                    yield end - length, owners
                jump = 1
            end += jump


def item_windows(benchmark: DataFrame, id_col: str = "item_id", text_col: str = "text", window: int = WINDOW) -> DataFrame:
    """Distinct (item string, words): the windows of all items; a shorter item with any words is one window."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(batches, "text"):
            for item, text in zip(piece.rows.column("item").to_pylist(), piece.raw()):
                words = words_of(text)
                wins = list({b" ".join(words[i : i + window]) for i in range(max(1, len(words) - window + 1))} - {b""})
                for lo in range(0, len(wins), 10_000):
                    part = wins[lo : lo + 10_000]
                    yield pa.RecordBatch.from_arrays([pa.array([item] * len(part), pa.string()), pa.array(part, pa.binary())], ["item", "words"])

    rows = benchmark.select(F.col(id_col).cast("string").alias("item"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "item string, words binary").distinct()


def _pass(shared):
    """A map-only pass of one block over rows (row, text, hit binary, items array)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, names = shared.value
        by_length: dict[int, dict] = defaultdict(lambda: defaultdict(list))
        for owner, joined in rows:
            words = tuple(joined.split(b" "))
            by_length[len(words)][words].append(owner)
        searches = [ShiftSearch(p, n) for n, p in by_length.items()]
        for piece in text_pieces(batches, "text"):
            old_hit, old_items = piece.rows.column("hit").to_pylist(), piece.rows.column("items").to_pylist()
            hits, items, counts = [], [], []
            for text, hit, known in zip(piece.raw(), old_hit, old_items):
                words = words_of(text)
                counts.append(len(words))
                found, marks = set(known), None
                for search in searches:
                    for start, owners in search.find(words):
                        if marks is None:
                            marks = np.zeros(len(words), bool)
                        marks[start : start + search.length] = True
                        found.update(names[i] for i in owners)
                if marks is not None:
                    bits = np.packbits(marks)
                    hit = (bits | np.frombuffer(hit, np.uint8)).tobytes() if hit else bits.tobytes()
                hits.append(hit)
                items.append(sorted(found))
            out = piece.rows.set_column(2, "hit", pa.array(hits, pa.binary())).set_column(3, "items", pa.array(items, pa.list_(pa.string())))
            yield out.set_column(4, "n_words", pa.array(counts, pa.int64()))

    return run


def _blocks(windows: DataFrame, limit: int) -> list[int]:
    """The block numbers of ``windows`` (with column bytes), each of about ``limit`` bytes of text."""
    total = windows.agg(F.coalesce(F.sum(F.length("words") + 64), F.lit(0))).first()[0]
    return list(range(max(1, -(-total // limit))))


def find_contamination(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text: str = "text", window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """``docs`` rows as (row struct of all columns, n_words, hit binary or null, items array<string>).

    ``hit`` packs one bit a word, most significant first. Null texts have no words; null item ids count as the item
    "null"; items without words have no window; repeated rows are judged alike; empty tables are allowed on both sides.
    """
    spark = docs.sparkSession
    named = benchmark.withColumn(item_col, F.coalesce(F.col(item_col).cast("string"), F.lit("null")))
    windows = settle(item_windows(named, item_col, item_text, window), "windows")
    blocks = _blocks(windows, block_bytes)
    rows = docs.select(
        F.struct(*docs.columns).alias("row"),
        F.col(text_col).alias("text"),
        F.lit(None).cast("binary").alias("hit"),
        F.array().cast("array<string>").alias("items"),
        F.lit(0).cast("long").alias("n_words"),
    )
    for k in blocks:
        part = windows.where(F.pmod(F.xxhash64("words"), F.lit(len(blocks))) == k).collect()  # of a bounded size
        names = sorted({r.item for r in part})
        at = {x: i for i, x in enumerate(names)}
        shared = spark.sparkContext.broadcast(([(at[r.item], bytes(r.words)) for r in part], names))
        rows = rows.mapInArrow(_pass(shared), rows.schema)
    release(windows)
    return rows.select("row", "n_words", "hit", "items")


def bits_set(hit: Column) -> Column:
    """How many bits of a binary column are set."""
    digits, ones = F.hex(hit), F.lit(0)
    for digit, n in zip("0123456789ABCDEF", (bin(i).count("1") for i in range(16))):
        ones = ones + n * (F.length(digits) - F.length(F.replace(digits, F.lit(digit), F.lit(""))))
    return F.coalesce(ones, F.lit(0)).cast("long")


def digest(found: DataFrame) -> DataFrame:
    """Counts and the hash of the item list in place of hits and items."""
    return found.select(
        "row", "n_words",
        bits_set(F.col("hit")).alias("n_hit"),
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.array_sort("items"), ",").cast("binary"), 256).alias("items_sha256"),
        F.col("hit").isNotNull().alias("contaminated"),
    )
