"""Fixed-width hashes of keys; those from md5 are the same in any engine."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def fp64(key: Column | str) -> Column:
    return F.xxhash64(key)


def _hex(key: Column | str) -> Column:
    return F.md5(F.col(key).cast("string") if isinstance(key, str) else key.cast("string"))


def fp60(key: Column | str, part: int = 0) -> Column:
    """15 hex digits of the md5 as a number; part 0 or 1."""
    return F.conv(F.substring(_hex(key), 1 + 15 * part, 15), 16, 10).cast("long")


def fp128(key: Column | str) -> Column:
    return _hex(key)


def expected_collisions(n: float, bits: int) -> float:
    return n * n / 2.0 ** (bits + 1)
