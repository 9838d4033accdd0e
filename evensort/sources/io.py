"""Scans and sinks: pruned tables, row positions, formats, sorted and bucketed output."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.sorter import SortedFrame


def load(spark: SparkSession, sf_dir: str, table: str, columns: Sequence[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df


def load_with_pos(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """Rows with ``pos``: the row's index in its file after the rows of files before it (by path)."""
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet").withColumns({"__file": F.col("_metadata.file_path"), "__row": F.col("_metadata.row_index")})
    sizes = df.groupBy("__file").agg(F.count("*").alias("n"))
    before = Window.orderBy("__file").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select(F.col("__file").alias("f"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    joined = df.join(starts, F.col("__file") == F.col("f"))
    return joined.withColumn("pos", (F.col("start") + F.col("__row")).cast("bigint")).drop("__file", "__row", "f", "start")


def views(spark: SparkSession, sf_dir: str, *tables: str) -> None:
    for t in tables:
        load(spark, sf_dir, t).createOrReplaceTempView(t)


def scratch(spark: SparkSession) -> str:
    """A fresh folder under the shared one, or a local one where none is named."""
    top = spark.conf.get("spark.checkpoint.dir", None)
    if top is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        top = tempfile.gettempdir()
    return f"{top}/evensort-{uuid.uuid4().hex}"


def roundtrip(df: DataFrame, fmt: str, **options) -> DataFrame:
    """Write in a format and read back with the same schema."""
    path = scratch(df.sparkSession)
    df.write.format(fmt).options(**options).save(path)
    return df.sparkSession.read.format(fmt).schema(df.schema).options(**options).load(path)


def write_sorted(sorted_: SortedFrame, path: str) -> None:
    """One folder a partition, rows in order inside: row-group statistics then skip ranges."""
    sorted_.df.repartitionById(sorted_.n_parts, F.col("part").cast("int")).sortWithinPartitions("part", "rnk").write.partitionBy("part").parquet(path)


def read_sorted(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def manifest(rows: DataFrame) -> DataFrame:
    """(part, part_offset, n, min_key, max_key) of a sorted layout."""
    return rows.groupBy(F.col("part").cast("bigint").alias("part")).agg(
        F.min("rnk").alias("part_offset"), F.count("*").alias("n"), F.min("key").alias("min_key"), F.max("key").alias("max_key")
    )


def save_bucketed(df: DataFrame, name: str, column: str, buckets: int = 8) -> DataFrame:
    df.write.bucketBy(buckets, column).sortBy(column).mode("overwrite").saveAsTable(name)
    return df.sparkSession.table(name)


def save_partitioned(df: DataFrame, column: str) -> DataFrame:
    path = scratch(df.sparkSession)
    df.write.partitionBy(column).parquet(path)
    return df.sparkSession.read.parquet(path)
