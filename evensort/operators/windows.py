"""Window functions over a whole order, without a single-partition window.

Every function works on a sorted layout: a window inside each part, shifted by figures of
the parts before it, one row a part.  Windows and figures group by the column that the
rows were shuffled by and read the same columns, so that one shuffle serves both."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .sorter import SortedFrame


def _carry(per_part: DataFrame, value: str, how) -> DataFrame:
    """(p, carried): ``how`` over the parts before each part."""
    w = Window.orderBy("__id").rowsBetween(Window.unboundedPreceding, -1)
    return per_part.select(F.col("__id").alias("p"), how(F.col(value)).over(w).alias("carried"))


def _join(rows: DataFrame, carried: DataFrame) -> DataFrame:
    # one row a part
    return rows.join(F.broadcast(carried), F.col("__id") == F.col("p")).drop("p")


def row_number(sorted_: SortedFrame) -> DataFrame:
    return sorted_.df.withColumn("rn", F.col("rnk") + 1)


def ntile(sorted_: SortedFrame, tiles: int) -> DataFrame:
    """SQL's tiles (larger ones first) from the rank alone; they differ from the parts when
    the row count is no multiple."""
    small, extra = divmod(sorted_.n, tiles)
    edge = extra * (small + 1)
    in_large = F.expr(f"rnk div {small + 1}")
    rest = F.expr(f"{extra} + (rnk - {edge}) div {max(1, small)}")
    return sorted_.df.withColumn("tile", (F.when(F.col("rnk") < edge, in_large).otherwise(rest) + 1).cast("bigint"))


def running_sum(sorted_: SortedFrame, value: Column) -> DataFrame:
    rows = sorted_.laid().withColumn("__v", value)
    own = Window.partitionBy("__id").orderBy("rnk").rowsBetween(Window.unboundedPreceding, 0)
    # the rank takes part so that the figures need the columns that the rows need
    totals = rows.groupBy("__id").agg(F.sum(F.when(F.col("rnk") >= 0, F.col("__v"))).alias("total"))
    out = _join(rows.withColumn("__own", F.sum("__v").over(own)), _carry(totals, "total", F.sum))
    return out.withColumn("running", F.col("__own") + F.coalesce("carried", F.lit(0))).drop("__v", "__own", "carried", "__id")


def dense_rank(sorted_: SortedFrame) -> DataFrame:
    """Runs of equal keys, numbered; a run that a cut divides is counted once."""
    w = Window.partitionBy("__id").orderBy("rnk")
    rows = sorted_.laid().withColumn("__before", F.lag(F.struct("key")).over(w))
    ends = rows.groupBy("__id").agg(F.max_by(F.struct("key"), "rnk").alias("last"))
    rows = _join(rows, _carry(ends, "last", lambda c: F.last(c, ignorenulls=True))).withColumnRenamed("carried", "__carried")
    new = ~F.coalesce("__before", "__carried").eqNullSafe(F.struct("key"))
    rows = rows.withColumn("__new", new.cast("bigint"))
    totals = rows.groupBy("__id").agg(F.sum("__new").alias("total"))
    own = F.sum("__new").over(w.rowsBetween(Window.unboundedPreceding, 0))
    out = _join(rows.withColumn("__own", own), _carry(totals, "total", F.sum))
    out = out.withColumn("dense_rank", F.col("__own") + F.coalesce("carried", F.lit(0)))
    return out.drop("__before", "__carried", "__new", "__own", "carried", "__id")


def lag(sorted_: SortedFrame, value: str) -> DataFrame:
    """The value of the row before, across part ends too; empty parts are passed over."""
    w = Window.partitionBy("__id").orderBy("rnk")
    rows = sorted_.laid().withColumn("__own", F.lag(F.struct(value)).over(w))
    ends = rows.groupBy("__id").agg(F.max_by(F.struct(value), "rnk").alias("last"))
    out = _join(rows, _carry(ends, "last", lambda c: F.last(c, ignorenulls=True)))
    return out.withColumn("before", F.coalesce("__own", "carried")[value]).drop("__own", "carried", "__id")
