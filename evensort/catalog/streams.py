"""Streaming queries over the events table."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..sources import io
from ..streaming import streams

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def _ntz(df, column):
    return df.withColumn(column, F.col(column).cast("timestamp_ntz"))


@query("stream_tumbling", "SELECT date_trunc('day', ts) AS window_start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, d):
    return _ntz(streams.drain(streams.tumbling(streams.events(spark, d), "1 day", "event_type"), "complete"), "window_start")


@query("stream_sliding", """WITH w AS (SELECT time_bucket(INTERVAL 6 HOUR, ts) - k * INTERVAL 6 HOUR AS window_start, event_type FROM events, (SELECT unnest(range(4)) AS k))
    SELECT window_start, event_type, count(*) AS n FROM w GROUP BY 1, 2""")  # fmt: skip
def stream_sliding(spark, d):
    return _ntz(streams.drain(streams.tumbling(streams.events(spark, d), "1 day", "event_type", "6 hours"), "complete"), "window_start")


@query("stream_session", """WITH g AS (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 12 HOUR THEN 0 ELSE 1 END AS new_one FROM events),
    s AS (SELECT *, sum(new_one) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM g)
    SELECT user_id, min(ts) AS session_start, count(*) AS n FROM s GROUP BY user_id, session""")  # fmt: skip
def stream_session(spark, d):
    return _ntz(streams.drain(streams.sessions(streams.events(spark, d), "12 hours", "user_id"), "complete"), "session_start")


@query("stream_late_drop", """WITH m AS (SELECT max(event_id) // 2 AS half, max(ts) - INTERVAL 1 HOUR AS mark FROM events)
    SELECT date_trunc('day', ts) AS window_start, event_type, count(*) AS n FROM events, m
    WHERE event_id > half AND date_trunc('day', ts) + INTERVAL 1 DAY <= mark GROUP BY 1, 2""")  # fmt: skip
def stream_late_drop(spark, d):
    """The younger half arrives first; the older half is late by then and dropped.

    A batch drops rows by the mark that the batch before it worked with, so the last event
    comes in a batch of its own between the halves."""
    last = io.load(spark, d, "events").agg(F.max("event_id")).first()[0]
    half = last // 2
    folder = streams.replay(spark, d, [f"event_id > {half} AND event_id < {last}", f"event_id = {last}", f"event_id <= {half}"])
    rows = streams.events(spark, folder, "*.parquet", files=1).withWatermark("at", "1 hour")
    return _ntz(streams.drain(streams.tumbling(rows, "1 day", "event_type"), "append"), "window_start")


@query("stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def stream_dedup(spark, d):
    """Every event arrives twice; duplicates inside the watermark are dropped."""
    folder = streams.replay(spark, d, ["true", "true"])
    rows = streams.events(spark, folder, "*.parquet", files=1).withWatermark("at", "400 days")
    once = rows.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type")
    return streams.drain(once, "append").groupBy("event_type").agg(F.count("*").alias("n"))


_WEIGHTS = (("view", 1), ("click", 2), ("purchase", 5))


@query("stream_static_join", "SELECT e.event_type, CAST(sum(CAST(round(e.value * 100) AS BIGINT) * w) AS BIGINT) AS weighted FROM events e JOIN (VALUES " + ", ".join(f"('{t}', {w})" for t, w in _WEIGHTS) + ") AS v(t, w) ON e.event_type = t GROUP BY e.event_type")
def stream_static_join(spark, d):
    weights = spark.createDataFrame(list(_WEIGHTS), "event_type string, w int")
    joined = streams.events(spark, d).join(F.broadcast(weights), "event_type")
    total = joined.groupBy("event_type").agg(F.sum(F.round(F.col("value") * 100).cast("bigint") * F.col("w")).alias("weighted"))
    return streams.drain(total, "complete")


@query("stream_interval_join", "SELECT a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_interval_join(spark, d):
    clicks = streams.events(spark, d).where("event_type = 'click'")
    bought = streams.events(spark, d).where("event_type = 'purchase'")
    return streams.drain(streams.interval_join(clicks, bought, "user_id", "1 HOUR"), "append")


@query("stream_reorder", "SELECT user_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS place, event_id FROM events")
def stream_reorder(spark, d):
    """Odd and even events arrive apart; a last event far ahead closes the stream."""
    folder = streams.replay(spark, d, ["event_id % 2 = 0", "event_id % 2 = 1"])
    tail = io.load(spark, d, "events").limit(1).withColumn("ts", F.lit("2200-01-01").cast("timestamp_ntz")).withColumn("user_id", F.lit(-1).cast("bigint"))
    import time

    time.sleep(1.1)
    tail.coalesce(1).write.mode("append").parquet(folder)
    rows = streams.events(spark, folder, "*.parquet", files=1).select("user_id", "event_id", "at")
    return streams.drain(streams.reorder(rows, "400 days"), "append").where("user_id >= 0")


@query("stream_sorted_runs", "SELECT event_id AS pos, CAST(round(value * 100) AS BIGINT) AS key, row_number() OVER (ORDER BY CAST(round(value * 100) AS BIGINT), event_id) - 1 AS rnk FROM events")
def stream_sorted_runs(spark, d):
    folder = streams.replay(spark, d, ["event_id % 3 = 0", "event_id % 3 = 1", "event_id % 3 = 2"])
    rows = streams.events(spark, folder, "*.parquet", files=1)
    return streams.sorted_runs(rows.select(F.col("event_id").alias("pos"), F.round(F.col("value") * 100).cast("bigint").alias("key")))
