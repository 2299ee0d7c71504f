"""Portable randomness: numbers from md5, the same in Spark, SQL engines and Python."""

from __future__ import annotations

from hashlib import md5

from pyspark.sql import Column
from pyspark.sql import functions as F

_DIGITS, _RANGE = 13, float(1 << 52)


def uniform(key: Column) -> Column:
    """A double in [0, 1) from a string."""
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, _DIGITS), 16, 10).cast("double") / F.lit(_RANGE)


def uniform_of(key: str) -> float:
    return int(md5(key.encode()).hexdigest()[:_DIGITS], 16) / _RANGE


def uniform_sql(key: str) -> str:
    """The same in DuckDB, for an SQL expression that is a string."""
    return f"(('0x' || md5({key})[1:{_DIGITS}])::BIGINT / {_RANGE!r})"


def gaussian_of(key: str) -> float:
    """About normal: twelve uniform numbers added up, less six."""
    return sum(uniform_of(f"{key}:{i}") for i in range(12)) - 6.0


def order_key(seed: str, id: str) -> Column:
    """What a random order by seed sorts by."""
    return F.md5(F.concat(F.lit(f"{seed}:"), F.col(id).cast("string")).cast("binary"))
