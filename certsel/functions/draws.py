"""Hash draws: every random number is a function of (key, seed, stream), so retries and partitioning change nothing."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SPACE = float(1 << 52)


def hashed(key: Column, seed: Column | int, stream: str) -> Column:
    """The first 13 hex digits of md5(key:seed:stream), as a long below 2^52."""
    s = seed if isinstance(seed, Column) else F.lit(seed)
    text = F.concat_ws(":", key.cast("string"), s.cast("string"), F.lit(stream))
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")


def fast_hashed(key: Column, seed: Column | int, stream: str) -> Column:
    """The same range from xxhash64: for runs that need no twin in another engine."""
    s = seed if isinstance(seed, Column) else F.lit(seed)
    return F.shiftrightunsigned(F.xxhash64(key.cast("string"), s, F.lit(stream)), 12)


def unit(h: Column) -> Column:
    return (h + F.lit(0.5)) / F.lit(SPACE)


def uniform(key: Column, seed: Column | int, stream: str) -> Column:
    return unit(hashed(key, seed, stream))
