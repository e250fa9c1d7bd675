"""Keyed randomness: a hash of a key and a salt, so that retries, repartitioning and SQL give the same draw."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def uniform(key: Column | str, salt: str) -> Column:
    """A number in [0, 1): the first 8 hex digits of md5(salt|key) over 2**32."""
    digest = F.md5(F.concat(F.lit(f"{salt}|"), _col(key).cast("string")).cast("binary"))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") / F.lit(float(1 << 32))


def hash_order(key: Column | str, salt: str) -> Column:
    """A hex string to order by: a shuffle that every engine repeats."""
    return F.md5(F.concat(F.lit(f"{salt}|"), _col(key).cast("string")).cast("binary"))
