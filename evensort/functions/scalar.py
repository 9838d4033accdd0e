"""Scalar functions on keys and partitions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .keys import count_bounds, literal, ordered_long


def partition_of(df: DataFrame, column: str, pivots: list) -> Column:
    """Number of pivots strictly below a column's value, in codegen."""
    kind = df.schema[column].dataType
    bounds = [F.struct(literal(p, kind).alias(column)) for p in pivots]
    return count_bounds(F.struct(F.col(column)), bounds, strict=True)


def codec_report(columns: dict[str, tuple[DataFrame, str]]) -> DataFrame:
    """(name, n, monotone): whether the long code of each column sorts and ties as it does.

    Distinct keys are laid out by range; neighbours inside a partition and the ends of
    partitions are compared, so no task sees a whole column."""
    from pyspark.sql import Window

    out = None
    for name, (df, c) in columns.items():
        coded = df.select(F.col(c).alias("key"), ordered_long(F.col(c), df.schema[c].dataType).alias("code"))
        groups = coded.groupBy("key").agg(F.count("*").alias("n"), F.min("code").alias("lo"), F.max("code").alias("hi"))
        laid = groups.repartitionByRange("key").withColumn("part", F.spark_partition_id()).persist()
        local = Window.partitionBy("part").orderBy("key")
        inside = laid.withColumn("last", F.lag("hi").over(local))
        sums = inside.agg(F.sum("n").alias("n"), F.bool_and((F.col("lo") == F.col("hi")) & (F.col("last").isNull() | (F.col("last") < F.col("lo")))).alias("ok"))
        ends = laid.groupBy("part").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
        between = ends.withColumn("last", F.lag("hi").over(Window.orderBy("part"))).agg(F.coalesce(F.bool_and(F.col("last").isNull() | (F.col("last") < F.col("lo"))), F.lit(True)).alias("apart"))
        own = sums.join(F.broadcast(between)).select(F.lit(name).alias("name"), "n", (F.col("ok") & F.col("apart")).alias("monotone"))
        out = own if out is None else out.unionByName(own)
    return out
