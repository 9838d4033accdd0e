"""Range filters that touch only the partitions whose key range meets them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .sorter import SortedFrame


def touched(sorted_: SortedFrame, lo, hi) -> tuple[int, int]:
    """First and last partition that may hold keys in [lo, hi], from the cuts alone."""
    keys = [c.key for c in sorted_.cuts]
    first = sum(k is None or k < lo for k in keys)
    last = sum(k is None or k <= hi for k in keys)
    return first, last


def between(sorted_: SortedFrame, lo, hi) -> DataFrame:
    first, last = touched(sorted_, lo, hi)
    return sorted_.parts(first, last).where(F.col("key").between(lo, hi))
