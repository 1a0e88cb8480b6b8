"""Zero-copy access to the text column of Arrow batches, in pieces of bounded size."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

#: Bytes of text that an operator holds at once, unless one text is longer.
PIECE_BYTES = 4 << 20


@dataclass
class TextPiece:
    """Rows ``lo`` to ``hi`` of an Arrow batch: the bytes of their texts and where each begins (one more at the end)."""

    rows: pa.RecordBatch
    data: np.ndarray
    starts: np.ndarray

    def raw(self) -> Iterator[bytes]:
        view = memoryview(self.data)
        at = self.starts.tolist()
        for a, b in zip(at, at[1:]):
            yield bytes(view[a:b])


def text_pieces(batches: Iterable[pa.RecordBatch], column: str = "text", limit: int = PIECE_BYTES) -> Iterator[TextPiece]:
    """Cuts Arrow batches to pieces of about ``limit`` text bytes. A null text counts as empty."""
    for batch in batches:
        if not batch.num_rows:
            continue
        texts = batch.column(column)
        if texts.null_count:
            texts = texts.fill_null("")
        texts = texts.cast(pa.large_binary())
        _, offsets, data = texts.buffers()
        at = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1]
        raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
        lo = 0
        while lo < batch.num_rows:
            hi = int(np.searchsorted(at, at[lo] + limit, "right")) - 1
            hi = min(batch.num_rows, max(hi, lo + 1))
            yield TextPiece(batch.slice(lo, hi - lo), raw[at[lo] : at[hi]], at[lo : hi + 1] - at[lo])
            lo = hi
