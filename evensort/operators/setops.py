"""Set operations on sorted sequences."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import sorter


def merge_sorted(a: DataFrame, b: DataFrame, n_parts: int) -> DataFrame:
    """(key, side, pos, rnk) of two sequences (pos, key) merged: the first side goes first
    among equal keys.  Both sides are routed by common exact cuts of their union."""
    both = a.withColumn("side", F.lit(0)).unionByName(b.withColumn("side", F.lit(1)))
    # positions of the second side follow the first's, so ties go by (side, pos)
    shift = (a.agg(F.max("pos")).first()[0] or 0) + 1
    seq = both.select(F.col("key"), "side", F.col("pos").alias("own"), (F.col("pos") + F.col("side") * shift).alias("pos"))
    n_blocks = 8
    out = sorter.parallel_sort(seq, "exact", n_blocks, n_parts).df
    return out.select("key", "side", F.col("own").alias("pos"), "rnk")
