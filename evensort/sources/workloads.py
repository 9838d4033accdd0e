"""The study's six input sequences on the given tables, and amplification.

Every sequence has ``pos`` (dense, 0-based) and ``key``; pair and particle carry payload.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.keys import mix32, mix62
from .io import load, load_with_pos

SEQUENCES = ("uniform_int", "uniform_float", "almost_sorted", "dup3", "pair", "particle")
STEP, SHIFT = 7919, 17


def sequence(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return {
        "uniform_int": _uniform_int,
        "uniform_float": _uniform_float,
        "almost_sorted": _almost_sorted,
        "dup3": _dup3,
        "pair": _pair,
        "particle": _particle,
        "uniform_int_large": _uniform_int_large,
        "dup3_large": _dup3_large,
        "particle_large": _particle_large,
    }[name](spark, sf_dir)


def _orders(spark, sf_dir, *columns):
    return load(spark, sf_dir, "orders", ["o_orderkey", *columns])


def _uniform_int(spark, sf_dir):
    return _orders(spark, sf_dir).select(F.col("o_orderkey").alias("pos"), mix32(F.col("o_orderkey")).alias("key"))


def _uniform_float(spark, sf_dir):
    return _orders(spark, sf_dir, "o_totalprice").select(F.col("o_orderkey").alias("pos"), (F.col("o_totalprice") / 500000).cast("float").alias("key"))


def _almost_sorted(spark, sf_dir):
    """0..N-1 with floor(sqrt N) places swapped pairwise; the swaps are a table of sqrt(N) rows."""
    events = load(spark, sf_dir, "events", ["event_id"])
    n = events.count()
    pairs = spark.range(math.isqrt(n) // 2).select(
        F.pmod(F.col("id") * 2 * STEP + SHIFT, F.lit(n)).alias("a"), F.pmod((F.col("id") * 2 + 1) * STEP + SHIFT, F.lit(n)).alias("b")
    )
    swaps = pairs.select(F.col("a").alias("at"), F.col("b").alias("to")).union(pairs.select("b", "a"))
    joined = events.join(swaps, F.col("event_id") == F.col("at"), "left")
    return joined.select(F.col("event_id").alias("pos"), F.coalesce("to", "event_id").alias("key"))


def _dup3(spark, sf_dir):
    status = F.col("o_orderstatus")
    key = F.when(status == "F", 0).when(status == "O", 1).otherwise(2)
    return _orders(spark, sf_dir, "o_orderstatus").select(F.col("o_orderkey").alias("pos"), key.cast("int").alias("key"))


def _pair(spark, sf_dir):
    orders = _orders(spark, sf_dir)
    return orders.select(F.col("o_orderkey").alias("pos"), mix62(F.col("o_orderkey"), orders.count()).alias("key"), F.col("o_orderkey").alias("idx"))


def _particle(spark, sf_dir):
    rows = load(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    e = lambda i: F.col("embedding")[i].cast("double")
    triple = lambda i: F.array(e(i), e(i + 1), e(i + 2))
    return rows.select(
        F.col("vec_id").alias("pos"), mix62(F.col("vec_id"), rows.count()).alias("key"), e(0).alias("mass"),
        triple(1).alias("position"), triple(4).alias("velocity"), triple(7).alias("acceleration"), e(10).alias("potential"),
    )


def _uniform_int_large(spark, sf_dir):
    rows = load_with_pos(spark, sf_dir, "lineitem").select("pos", "l_extendedprice")
    return rows.select("pos", F.round(F.col("l_extendedprice") * 100).cast("bigint").alias("key"))


def _dup3_large(spark, sf_dir):
    rows = load_with_pos(spark, sf_dir, "lineitem").select("pos", "l_returnflag")
    flag = F.col("l_returnflag")
    return rows.select("pos", F.when(flag == "A", 0).when(flag == "N", 1).otherwise(2).cast("int").alias("key"))


def _particle_large(spark, sf_dir):
    rows = load_with_pos(spark, sf_dir, "lineitem")
    return rows.withColumn("key", mix32(F.col("pos")))


def amplify(seq: DataFrame, times: int, n: int | None = None, fresh_keys: bool = True) -> DataFrame:
    """``times`` copies end to end; keys are mixed anew from the position if ``fresh_keys``."""
    n = seq.count() if n is None else n
    copies = seq.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
    copies = copies.withColumn("pos", F.col("pos") + F.col("copy") * n).drop("copy")
    return copies.withColumn("key", mix32(F.col("pos"))) if fresh_keys else copies
