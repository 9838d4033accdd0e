"""Choosing a method and a cut strategy, and checks of physical plans."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Distinct keys up to which one histogram aggregation finds the cuts.
HISTOGRAM_KEYS = 1_000_000


def profile(seq: DataFrame) -> tuple[int, int, int]:
    """(rows, approximate distinct keys, rows of the most frequent key)."""
    n, distinct = seq.agg(F.count("*"), F.approx_count_distinct("key")).first()
    if distinct > HISTOGRAM_KEYS:
        return n, distinct, 0
    top = seq.groupBy("key").count().agg(F.max("count")).first()[0] or 0
    return n, distinct, top


def choose(seq: DataFrame, n_parts: int, ranks: bool = True) -> tuple[str, str]:
    """(method, strategy): native without ranks or balance; regular if no key can unbalance
    the partitions; else exact, by histogram for few keys and sketches for many."""
    if not ranks:
        return "native", "none"
    n, distinct, top = profile(seq)
    strategy = "histogram" if distinct <= HISTOGRAM_KEYS else "sketch_refine"
    if top < n / (2 * n_parts) and distinct > n / 2:
        return "regular", "none"
    return "exact", strategy


def merge_rule(row_bytes: int, runs: int) -> str:
    """Structured merging for wide rows of few runs, sorting again otherwise."""
    return "auto" if row_bytes >= 64 and runs <= 64 else "resort"


def executed(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges(df: DataFrame) -> list[str]:
    """The partitionings of a plan's shuffles."""
    return re.findall(r"Exchange (?!.*ReusedExchange)(\w+)", executed(df))
