"""Folds and bounded samples of labelled rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def fold(id: str = "doc_id", folds: int = 5) -> Column:
    """crc32 of the id as text, modulo ``folds``; null for a null id."""
    return F.pmod(F.crc32(F.col(id).cast("string").cast("binary")), F.lit(folds))


def bounded(rows: DataFrame, label: str, classes: list, each: int, id: str = "doc_id", seed: int = 7) -> DataFrame:
    """``each`` rows of every class at most, those of the smallest seeded hashes of the id."""
    out = None
    for value in classes:
        one = rows.where(F.col(label) == value).orderBy(F.xxhash64(F.lit(seed), F.col(id)), id).limit(each)
        out = one if out is None else out.unionByName(one)
    return out
