"""Ranks, pages, top-k and order statistics on sorted layouts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import pivots
from .sorter import SortedFrame


def part_of_rank(rank: int, n: int, n_parts: int) -> int:
    """The exact layout's partition of a 0-based rank."""
    return rank * n_parts // n if n else 0


def slice(sorted_: SortedFrame, first: int, last: int) -> DataFrame:
    """Rows of ranks first..last; rows of parts that don't hold them are not shuffled."""
    lo, hi = (part_of_rank(r, sorted_.n, sorted_.n_parts) for r in (first, last))
    return sorted_.parts(lo, hi).where(F.col("rnk").between(first, last))


def top_k(sorted_: SortedFrame, k: int) -> DataFrame:
    return slice(sorted_, 0, min(k, sorted_.n) - 1)


def exact_ranks(seq: DataFrame, ranks: list[int], strategy: str = "auto") -> list:
    """Keys of the given 1-based ranks, by exact cuts: no sort."""
    return [c.key for c in pivots.exact(seq, len(ranks) + 1, strategy, ranks=ranks)]


def exact_quantiles(seq: DataFrame, shares: list[float], strategy: str = "auto") -> list:
    """The key of rank max(1, ceil(share n)) for each share: an element, never interpolated."""
    n = seq.count()
    return exact_ranks(seq, [max(1, -int(-s * n // 1)) for s in shares], strategy)
