"""Words of many texts at once: where they lie and a 64-bit hash of each, without a Python step for each word.

A word's hash is a polynomial over its bytes modulo 2^64, read off prefix sums, and then mixed; it depends on the word's
bytes alone. Hashes of runs of words are polynomials over the hashes of the words.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

_RANDOM = np.random.default_rng(20)
_BYTE = _RANDOM.integers(0, 1 << 64, 256, dtype=np.uint64)
_BASE = 0x9E3779B97F4A7C15 | 3
_INVERSE = pow(_BASE, -1, 1 << 64)
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: ASCII white space, which is also what ``bytes.split`` cuts at.
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
_powers: dict[str, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """Spreads every bit of ``x`` over the whole word."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(32))


def _power(name: str, base: int, size: int) -> np.ndarray:
    if name not in _powers or len(_powers[name]) < size:
        out = np.full(max(size, 1 << 20), np.uint64(base))
        out[0] = 1
        _powers[name] = np.cumprod(out, dtype=np.uint64)
    return _powers[name][:size]


class Prefix:
    """Hashes of any byte ranges of ``data``."""

    def __init__(self, data: np.ndarray):
        self.sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(_BYTE[data] * _power("up", _BASE, len(data)), out=self.sums[1:])

    def of(self, begin: np.ndarray, end: np.ndarray, salt: int = 0) -> np.ndarray:
        down = _power("down", _INVERSE, len(self.sums))
        return mix((self.sums[end] - self.sums[begin]) * down[begin] + np.uint64(salt * 0xD6E8FEB86659FD93 % (1 << 64)) + (end - begin).astype(np.uint64))


@dataclass
class Words:
    """``begin`` and ``end`` of each word in the lower-cased bytes, the text it lies in and its hash."""

    lower: np.ndarray
    begin: np.ndarray
    end: np.ndarray
    owner: np.ndarray
    value: np.ndarray


def words_of(data: np.ndarray, starts: np.ndarray) -> Words:
    """The words of the texts that begin at ``starts`` (one more at the end); no word crosses texts."""
    lower = LOWER[data]
    solid = np.zeros(len(data) + 2, bool)
    solid[1:-1] = ~SPACE[data]
    cut = np.zeros(len(data) + 1, bool)
    cut[starts] = True
    begin = np.flatnonzero(solid[1:] & (~solid[:-1] | cut))
    end = np.flatnonzero(solid[:-1] & (~solid[1:] | cut))
    owner = np.searchsorted(starts, begin, "right") - 1
    return Words(lower, begin, end, owner, Prefix(lower).of(begin, end))


def run_hashes(value: np.ndarray, width: int, salt: int = 0) -> np.ndarray:
    """The hash of the ``width`` words that begin at each word."""
    size = len(value) - width + 1
    if size <= 0:
        return np.zeros(0, np.uint64)
    out = np.full(size, np.uint64(salt * 2 + 1))
    for i in range(width):
        out = out * np.uint64(_BASE) + value[i : i + size]
    return mix(out)


def shingles_of(value: np.ndarray, bounds: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, bounds): the shingles of ``width`` words of each group of words; a shorter group is one shingle.

    ``bounds`` holds the first word of each group and one more; no group is empty.
    """
    sizes = np.diff(bounds)
    counts = np.maximum(1, sizes - width + 1)
    out_bounds = np.r_[0, np.cumsum(counts)]
    long = run_hashes(value, width)
    at = np.repeat(bounds[:-1] - out_bounds[:-1], counts) + np.arange(out_bounds[-1])
    few = sizes < width
    out = long[np.minimum(at, max(0, len(long) - 1))] if len(long) else np.zeros(len(at), np.uint64)
    if few.any():
        first, size = bounds[:-1][few], sizes[few]
        whole = size.astype(np.uint64)
        for i in range(width - 1):
            whole = np.where(i < size, whole * np.uint64(_BASE) + value[np.minimum(first + i, len(value) - 1)], whole)
        out[out_bounds[:-1][few]] = mix(whole ^ np.uint64(0xA5A5A5A5A5A5A5A5))
    return out, out_bounds


def window_least(value: np.ndarray, size: int) -> np.ndarray:
    """The place of the least value (by its upper 32 bits, the left of equals) among ``size`` neighbours, from each."""
    least = (value & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(value), dtype=np.uint64)
    width = 1
    while width * 2 <= size:
        least = np.minimum(least[:-width], least[width:])
        width *= 2
    if width < size:
        least = np.minimum(least[: len(least) - (size - width)], least[size - width :])
    return (least & np.uint64(0xFFFFFFFF)).astype(np.int64)
