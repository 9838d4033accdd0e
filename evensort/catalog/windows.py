"""Window functions, sorts, limits and top-k."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.keys import By
from ..operators import rank, sorter, windows
from ..sources import io
from .relational import RANKED, by_price

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def same(name: str, table: str, sql: str, spark_sql: str | None = None) -> None:
    def run(spark, d):
        io.views(spark, d, *table.split())
        return spark.sql(spark_sql or sql)

    query(name, sql)(run)


_PER = "PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey"
same("win_ranking", "orders", f"SELECT o_orderkey, CAST(row_number() OVER ({_PER}) AS BIGINT) AS rn, CAST(rank() OVER ({_PER}) AS BIGINT) AS rk, CAST(dense_rank() OVER ({_PER}) AS BIGINT) AS dr, CAST(ntile(4) OVER ({_PER}) AS BIGINT) AS nt FROM orders")
same("win_percent", "orders", f"SELECT o_orderkey, round(percent_rank() OVER ({_PER}), 6) AS pr, round(cume_dist() OVER ({_PER}), 6) AS cd FROM orders")
_U = "PARTITION BY user_id ORDER BY ts, event_id"
_WHOLE = "ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING"
same("win_offset", "events", f"SELECT event_id, lag(event_id) OVER ({_U}) AS before, lead(event_id) OVER ({_U}) AS after, first_value(event_id) OVER ({_U} {_WHOLE}) AS first_id, last_value(event_id) OVER ({_U} {_WHOLE}) AS last_id, nth_value(event_id, 2) OVER ({_U} {_WHOLE}) AS second_id FROM events")
_CENTS = "CAST(round(value * 100) AS BIGINT)"
same("win_rows_frame", "events", f"SELECT event_id, CAST(sum({_CENTS}) OVER ({_U} ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS BIGINT) AS cents FROM events")
same("win_range_frame", "events", f"SELECT event_id, CAST(sum({_CENTS}) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS BIGINT) AS cents FROM events", f"SELECT event_id, CAST(sum({_CENTS}) OVER (PARTITION BY user_id ORDER BY CAST(ts AS TIMESTAMP) RANGE BETWEEN INTERVAL '1' DAY PRECEDING AND CURRENT ROW) AS BIGINT) AS cents FROM events")
_GAP = "CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL {} THEN 0 ELSE 1 END"
same("win_sessions", "events", *[f"WITH g AS (SELECT user_id, ts, event_id, {_GAP.format(i)} AS new_one FROM events), s AS (SELECT *, CAST(sum(new_one) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS session FROM g) SELECT user_id, session, count(*) AS n, min(ts) AS session_start FROM s GROUP BY user_id, session" for i in ("12 HOUR", "'12' HOUR")])


def by_date(spark, d) -> sorter.SortedFrame:
    rows = io.load(spark, d, "orders", ["o_orderkey", "o_orderdate", "o_totalprice"])
    return sorter.parallel_sort(rows.select(F.col("o_orderkey").alias("pos"), F.col("o_orderdate").alias("key"), "o_totalprice"), "exact", 8, 8)


_G = "ORDER BY o_orderdate, o_orderkey"


@query("win_global_row_number", f"SELECT o_orderkey AS pos, row_number() OVER ({_G}) AS rn FROM orders")
def win_global_row_number(spark, d):
    return windows.row_number(by_date(spark, d)).select("pos", "rn")


@query("win_global_dense_rank", "SELECT o_orderkey AS pos, dense_rank() OVER (ORDER BY o_orderdate) AS dense_rank FROM orders")
def win_global_dense_rank(spark, d):
    return windows.dense_rank(by_date(spark, d)).select("pos", "dense_rank")


@query("win_global_running_sum", f"SELECT o_orderkey AS pos, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) OVER ({_G} ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS running FROM orders")
def win_global_running_sum(spark, d):
    return windows.running_sum(by_date(spark, d), F.round(F.col("o_totalprice") * 100).cast("bigint")).select("pos", "running")


@query("win_global_ntile", f"SELECT o_orderkey AS pos, ntile(7) OVER ({_G}) AS tile, ((row_number() OVER ({_G}) - 1) * 8) // count(*) OVER () AS part FROM orders")
def win_global_ntile(spark, d):
    return windows.ntile(by_date(spark, d), 7).select("pos", "tile", "part")


@query("win_global_lag", f"SELECT o_orderkey AS pos, lag(o_orderkey) OVER ({_G}) AS before FROM orders")
def win_global_lag(spark, d):
    return windows.lag(by_date(spark, d), "pos").select("pos", "before")


# ---- sorts ----


@query("sort_multi_key", "SELECT o_orderkey, row_number() OVER (ORDER BY o_orderpriority, o_totalprice DESC, o_orderkey) - 1 AS rnk FROM orders")
def sort_multi_key(spark, d):
    rows = sorter.sequence(io.load(spark, d, "orders"), ["o_orderpriority", By("o_totalprice", desc=True)], pos="o_orderkey")
    return sorter.parallel_sort(rows.select("pos", "key"), "exact", 8, 8).df.select(F.col("pos").alias("o_orderkey"), "rnk")


@query("sort_desc_nulls", "SELECT d.doc_id, row_number() OVER (ORDER BY l.quality DESC NULLS LAST, d.doc_id) - 1 AS rnk FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def sort_desc_nulls(spark, d):
    docs = io.load(spark, d, "documents", ["doc_id"]).join(io.load(spark, d, "labels"), "doc_id", "left")
    rows = sorter.sequence(docs, [By("quality", desc=True, nulls_last=True)], pos="doc_id")
    return sorter.parallel_sort(rows.select("pos", "key"), "exact", 8, 8).df.select(F.col("pos").alias("doc_id"), "rnk")


def _typed(name, key_sql, key_expr):
    sql = f"WITH r AS (SELECT o_orderkey AS pos, row_number() OVER (ORDER BY {key_sql}, o_orderkey) - 1 AS rnk, count(*) OVER () AS n FROM orders) SELECT pos, (rnk * 8) // n AS part, rnk FROM r"

    @query(name, sql)
    def run(spark, d):
        rows = io.load(spark, d, "orders").select(F.col("o_orderkey").alias("pos"), F.expr(key_expr).alias("key"))
        return sorter.parallel_sort(rows, "exact", 8, 8).df.select("pos", "part", "rnk")


_typed("sort_dates_orders", "o_orderdate", "o_orderdate")
_typed("sort_decimal_price", "CAST(o_totalprice AS DECIMAL(12, 2))", "CAST(o_totalprice AS DECIMAL(12, 2))")
_typed("sort_struct_key", "o_orderstatus, o_orderpriority", "struct(o_orderstatus, o_orderpriority)")


@query("sort_strings_documents", "WITH r AS (SELECT doc_id AS pos, row_number() OVER (ORDER BY text, doc_id) - 1 AS rnk, count(*) OVER () AS n FROM documents) SELECT pos, (rnk * 8) // n AS part, rnk FROM r")
def sort_strings_documents(spark, d):
    rows = io.load(spark, d, "documents", ["doc_id", "text"]).select(F.col("doc_id").alias("pos"), F.col("text").alias("key"))
    return sorter.parallel_sort(rows, "exact", 8, 8).df.select("pos", "part", "rnk")



# ---- limits and top-k ----

same("topk_orders", "orders", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100")
same("bottomk_orders", "orders", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 100")
same("topk_per_group", "orders", f"SELECT o_custkey, o_orderkey, CAST(rn AS BIGINT) AS rn FROM (SELECT o_custkey, o_orderkey, row_number() OVER ({_PER}) AS rn FROM orders) AS t WHERE rn <= 3")
same("topk_with_ties", "part", "SELECT p_partkey, p_size FROM (SELECT p_partkey, p_size, rank() OVER (ORDER BY p_size DESC) AS rk FROM part) AS t WHERE rk <= 10")
same("limit_offset_page", "orders", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 50 OFFSET 200")


@query("topk_by_cuts", f"WITH {RANKED} SELECT pos, key, rnk FROM r WHERE rnk < 100")
def topk_by_cuts(spark, d):
    return rank.top_k(by_price(spark, d, 16), 100).select("pos", "key", "rnk")
