"""Choices that depend on sizes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.formats import LAZY_ADDS


def choose_external(active_limbs: int, memory_bytes: int) -> str:
    """'scan' if one accumulator fits the memory of a task, else 'sort'.

    A double has at most 72 limbs, so IEEE data is always scanned; sorting is for exponents without bound.
    """
    return "scan" if active_limbs * 16 <= memory_bytes else "sort"


def needs_wide(rows: int) -> bool:
    """Could lazy BIGINT digit sums overflow?"""
    return rows >= LAZY_ADDS


def choose_combine(df: DataFrame, keys: list[str], rows: int) -> bool:
    """Is it worth combining before the shuffle?  Not where almost every row has a key of its own."""
    if not keys:
        return True
    groups = df.agg(F.approx_count_distinct(F.struct(*keys))).first()[0]
    return groups * 2 < rows
