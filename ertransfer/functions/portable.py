"""Hashes, draws and splits that Spark and other SQL engines compute alike; no result hangs on partitioning or retries."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def h32(*parts: Column | str) -> Column:
    """First 32 bits of the MD5 of the joined parts, as a long; strings are literals."""
    joined = F.concat(*[F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts])
    return F.conv(F.substring(F.md5(joined), 1, 8), 16, 10).cast("long")


def unit(*parts: Column | str) -> Column:
    """A number in (0, 1) drawn by the hash of the parts."""
    return (h32(*parts) + 0.5) / float(1 << 32)


def pair_key() -> Column:
    """Names a pair of tuples of a dataset."""
    return F.concat_ws(":", "dataset", F.col("id_l").cast("string"), F.col("id_r").cast("string"))


def pair_draw(seed: str) -> Column:
    """A number from 0 to 99 for each pair."""
    return h32(f"{seed}:", pair_key()) % 100
