"""Structured Streaming pieces around sorting.

Event times are TIMESTAMP_NTZ in the files; watermarks need TIMESTAMP, so they are cast in
the session zone (UTC) and cast back by the caller.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators import sorter
from ..sources import io

REORDERED = T.StructType([T.StructField("user_id", T.LongType()), T.StructField("place", T.LongType()), T.StructField("event_id", T.LongType())])


def events(spark: SparkSession, folder: str, pattern: str = "events.parquet", files: int | None = None) -> DataFrame:
    """The event files of a folder as a stream, oldest first; ``at`` is the event time."""
    schema = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
    reader = spark.readStream.schema(schema).option("pathGlobFilter", pattern)
    if files:
        reader = reader.option("maxFilesPerTrigger", files)
    return reader.parquet(folder).withColumn("at", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str, each: Callable[[DataFrame, int], None] | None = None) -> DataFrame:
    """Run a stream over what is there and return its output: the last batch in complete
    mode, all batches' rows otherwise."""
    spark, out = stream.sparkSession, io.scratch(stream.sparkSession)

    def write(batch: DataFrame, number: int) -> None:
        # a batch that runs again writes to the same folder
        batch.write.mode("overwrite").parquet(f"{out}/data/b{0 if mode == 'complete' else number}")

    job = stream.writeStream.outputMode(mode).foreachBatch(each or write).option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start()
    job.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{out}/data/*") if each is None else spark.range(0).toDF("none")


def tumbling(stream: DataFrame, size: str, by: str, slide: str | None = None) -> DataFrame:
    """(window_start, by, n) of tumbling or sliding windows."""
    w = F.window("at", size, slide) if slide else F.window("at", size)
    return stream.groupBy(w.alias("w"), by).agg(F.count("*").alias("n")).select(F.col("w.start").alias("window_start"), by, "n")


def sessions(stream: DataFrame, gap: str, by: str) -> DataFrame:
    grouped = stream.groupBy(F.session_window("at", gap).alias("w"), by).agg(F.count("*").alias("n"))
    return grouped.select(by, F.col("w.start").alias("session_start"), "n")


def interval_join(left: DataFrame, right: DataFrame, by: str, within: str, delay: str = "2 hours") -> DataFrame:
    """Pairs (left_id, right_id) of one ``by`` where right follows left within an interval;
    state is bounded by the watermarks."""
    a = left.withWatermark("at", delay).select(F.col(by).alias("a_by"), F.col("event_id").alias("left_id"), F.col("at").alias("a_at"))
    b = right.withWatermark("at", delay).select(F.col(by).alias("b_by"), F.col("event_id").alias("right_id"), F.col("at").alias("b_at"))
    return a.join(b, F.expr(f"a_by = b_by AND b_at > a_at AND b_at <= a_at + INTERVAL {within}")).select("left_id", "right_id")


def reorder(stream: DataFrame, delay: str) -> DataFrame:
    """(user_id, place, event_id): each user's events in time order, released once the
    watermark has passed them.  State holds the events not yet released and a counter."""
    state = T.StructType([T.StructField("n", T.LongType()), T.StructField("at", T.ArrayType(T.LongType())), T.StructField("ids", T.ArrayType(T.LongType()))])

    def run(key, frames: Iterator[pd.DataFrame], group) -> Iterator[pd.DataFrame]:
        n, held = 0, []
        if group.exists:
            n, at, ids = group.get
            held = list(zip(at, ids))
        for frame in frames:
            held += list(zip(frame["at"].astype("datetime64[us]").astype("int64").tolist(), frame["event_id"].tolist()))
        mark = group.getCurrentWatermarkMs() * 1000
        ready = sorted(h for h in held if h[0] <= mark)
        held = [h for h in held if h[0] > mark]
        group.update((n + len(ready), [h[0] for h in held], [h[1] for h in held]))
        if held:
            group.setTimeoutTimestamp(max(min(h[0] for h in held) // 1000 + 1, group.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"user_id": [key[0]] * len(ready), "place": range(n + 1, n + 1 + len(ready)), "event_id": [h[1] for h in ready]})

    marked = stream.withWatermark("at", delay)
    return marked.groupBy("user_id").applyInPandasWithState(run, REORDERED, state, "append", "EventTimeTimeout")


def sorted_runs(stream: DataFrame, n_parts: int = 4) -> DataFrame:
    """(pos, key, rnk): every micro-batch is sorted into a run of its own; at the end the runs
    are the blocks of one exact merge.  An external sort over time."""
    spark, out = stream.sparkSession, io.scratch(stream.sparkSession)

    def write(batch: DataFrame, number: int) -> None:
        batch.persist()
        run = sorter.parallel_sort(batch, "exact", 2, n_parts).df
        run.sortWithinPartitions("rnk").withColumn("run", F.lit(number)).write.mode("overwrite").parquet(f"{out}/runs/r{number}")
        batch.unpersist()

    drain(stream, "append", write)
    runs = spark.read.parquet(f"{out}/runs/*")
    return sorter.parallel_sort(runs.select("pos", "key"), "exact", 4, n_parts).df.select("pos", "key", "rnk")


def replay(spark: SparkSession, sf_dir: str, parts: list[str]) -> str:
    """A folder with one event file for each condition, in that order of age."""
    import time

    folder = io.scratch(spark)
    every = io.load(spark, sf_dir, "events")
    for i, condition in enumerate(parts):
        every.where(condition).coalesce(1).write.mode("append").parquet(folder)
        if i + 1 < len(parts):
            time.sleep(1.1)  # file order is by modification time, in seconds on some stores
    return folder

