"""Folds and bounded samples by hashes of ids: the same rows at every size, on every run."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FOLDS = 5


def fold(id: str = "doc_id") -> Column:
    """crc32 of the id's text modulo 5; null for a null id."""
    return F.pmod(F.crc32(F.col(id).cast("string").cast("binary")), F.lit(FOLDS))


def held_out(id: str = "doc_id") -> Column:
    """Rows of fold 0. A row without an id is neither held out nor learned from."""
    return F.coalesce(fold(id) == 0, F.lit(False))


def trainable(id: str = "doc_id") -> Column:
    return F.coalesce(fold(id) != 0, F.lit(False))


def bounded(rows: DataFrame, bound: int, id: str = "doc_id", salt: int = 0) -> DataFrame:
    """About `bound` rows (all, if there are fewer): those whose hashed id falls under a share. Nothing is collected."""
    n = rows.select(id).count()
    if n <= bound:
        return rows
    share = int(bound / n * (1 << 30))
    return rows.where(F.pmod(F.xxhash64(F.col(id), F.lit(salt)), F.lit(1 << 30)) < share)
