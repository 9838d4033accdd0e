"""Aggregates on sorted layouts, where exact cuts may divide a key's run."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import pivots
from .sorter import SortedFrame


def sorted_group_counts(sorted_: SortedFrame) -> DataFrame:
    """(key, n): run lengths inside each part, then runs of a key in several parts summed.

    Parts are grouped by the column they were shuffled by, so no row moves again; what
    crosses parts is one row a run."""
    runs = sorted_.laid().groupBy("__id", "key").agg(F.count("*").alias("n"))
    return runs.groupBy("key").agg(F.sum("n").alias("n"))


def distinct_by_sort(sorted_: SortedFrame) -> DataFrame:
    """Distinct keys: first of each run in a part, unless the last key before the part is the
    same.  Heads and ends read the same columns of one shuffle; only one key a part crosses parts."""
    laid = sorted_.laid()
    first = Window.partitionBy("__id").orderBy("rnk")
    heads = laid.select("__id", "key", F.lag(F.struct("key")).over(first).alias("before")).where("before IS NULL OR NOT (before.key <=> key)")
    ends = laid.groupBy("__id").agg(F.max_by(F.struct("key"), "rnk").alias("last"))
    # one row a partition; empty parts have none, so lag skips them
    ends = ends.select("__id", F.lag("last").over(Window.orderBy("__id")).alias("carried"))
    joined = heads.join(F.broadcast(ends), "__id")
    return joined.where("NOT (before IS NULL AND carried IS NOT NULL AND carried.key <=> key)").select("key")


def group_quantiles(df: DataFrame, group: str, column: str, shares: list[float]) -> DataFrame:
    """(group, share, value): elements of rank max(1, ceil(share n)) in each group, from a
    histogram by (group, value) and two-level sums: no group is collected."""
    counts = df.select(F.struct(F.col(group).alias("g"), F.col(column).alias("v")).alias("key")).groupBy("key").agg(F.count("*").alias("n"))
    summed = pivots.running_counts(counts)
    sizes = df.groupBy(F.col(group).alias("g")).agg(F.count("*").alias("size"))
    base = summed.groupBy(F.col("key.g").alias("g")).agg(F.min("less").alias("base"))
    want = sizes.join(base, "g").select("g", "base", F.explode(F.array(*[F.struct(F.lit(s).alias("share"), F.greatest(F.lit(1), F.ceil(F.lit(s) * F.col("size"))).alias("rank")) for s in shares])).alias("w"))
    held = summed.select("key.*", "n", "less").join(want, "g").where("less - base < w.rank AND w.rank <= less - base + n")
    return held.select(F.col("g").alias(group), F.col("w.share").alias("share"), F.col("v").alias("value"))
