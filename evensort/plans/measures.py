"""Cost and accuracy measures of sorts."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.partition import part_sizes


def elapsed(run: Callable[[], DataFrame], runs: int = 20) -> dict:
    """Mean seconds of materialising ``run()`` into nowhere; one run first, uncounted."""
    times = []
    for i in range(runs + 1):
        began = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        times.append(time.perf_counter() - began)
    return {"mean": statistics.mean(times[1:]), "stdev": statistics.pstdev(times[1:]), "runs": runs}


def efficiency(times: DataFrame) -> DataFrame:
    """(method, t, efficiency) from (method, t, sec): T(1) / (t T(t)), each method's own T(1)."""
    one = times.where("t = 1").select("method", F.col("sec").alias("one"))
    return times.join(one, "method").select("method", "t", F.round(F.col("one") / (F.col("t") * F.col("sec")), 6).alias("efficiency"))


def speed_ratio(times: DataFrame, baseline: str) -> DataFrame:
    """(method, t, ratio): the baseline's seconds over the method's."""
    base = times.where(F.col("method") == baseline).select("t", F.col("sec").alias("base"))
    return times.join(base, "t").select("method", "t", F.round(F.col("base") / F.col("sec"), 6).alias("ratio"))


def balance(routed: DataFrame, n_parts: int) -> DataFrame:
    """(n_parts, n_rows, max_n, min_n, imbalance): imbalance is the largest size over the mean."""
    sizes = part_sizes(routed, n_parts).agg(F.sum("n").alias("n_rows"), F.max("n").alias("max_n"), F.min("n").alias("min_n"))
    share = F.round(F.col("max_n") * n_parts / F.col("n_rows"), 6)
    return sizes.select(F.lit(n_parts).cast("bigint").alias("n_parts"), "n_rows", "max_n", "min_n", share.alias("imbalance"))


def merge_bound(routed: DataFrame, n_parts: int) -> DataFrame:
    """(t, max_n, bound): the efficiency that the largest partition allows, (N / n_P) / max."""
    b = balance(routed, n_parts)
    return b.select(F.col("n_parts").alias("t"), "max_n", F.round(F.col("n_rows") / (F.col("n_parts") * F.col("max_n")), 6).alias("bound"))


def pivot_only_lower_bound(seq: DataFrame) -> DataFrame:
    """(n_rows, distinct_keys, top_count): no layout that keeps equal keys together has a
    largest partition under the most frequent key's count."""
    counts = seq.groupBy("key").agg(F.count("*").alias("n"))
    return counts.agg(F.sum("n").alias("n_rows"), F.count("*").alias("distinct_keys"), F.max("n").alias("top_count"))


def selection_cost(spark: SparkSession, n: int, grid: list[tuple[int, int]]) -> DataFrame:
    """Model counts of pivot selection for (n_B, n_P): samples of regular sampling, and rounds
    and probes of an exact search whose rounds leave three quarters at most."""
    rows = spark.createDataFrame([(n, b, p) for b, p in grid], "n long, n_blocks long, n_parts long")
    rounds = F.ceil(F.ln(F.col("n").cast("double")) / F.ln(F.lit(4.0 / 3.0))) + 1
    return rows.select(
        "n", "n_blocks", "n_parts", (F.col("n_blocks") * (F.col("n_parts") - 1)).alias("samples"), rounds.cast("bigint").alias("max_rounds"),
        (rounds * F.col("n_blocks") * (F.col("n_parts") - 1)).cast("bigint").alias("max_probes"),
    )


def check_sorted(rows: DataFrame) -> DataFrame:
    """(n, inversions, overlaps): descents inside partitions, and partitions whose first key
    is under the last key of the one before.  Both are 0 in a sorted layout."""
    inside = Window.partitionBy("part").orderBy("rnk")
    down = rows.select("part", "key", F.lag("key").over(inside).alias("before")).agg(F.count("*").alias("n"), F.count_if(F.struct("key") < F.struct(F.col("before").alias("key"))).alias("inversions"))
    ends = rows.groupBy("part").agg(F.min(F.struct("key")).alias("lo"), F.max(F.struct("key")).alias("hi"))
    # one row a partition
    over = ends.select("lo", F.lag("hi").over(Window.orderBy("part")).alias("last")).agg(F.count_if(F.col("lo") < F.col("last")).alias("overlaps"))
    return down.join(F.broadcast(over))


def presortedness(seq: DataFrame, n: int) -> DataFrame:
    """(n, descents, max_displacement): rows below their predecessor, and how far a row moves
    at most.  Neighbours are joined by position, so no task needs the whole order."""
    after = seq.select((F.col("pos") - 1).alias("pos"), F.col("key").alias("following"))
    descents = seq.select("pos", "key").join(after, "pos").agg(F.count_if(F.col("following") < F.col("key")).alias("descents"))
    from ..operators.sorter import parallel_sort

    moved = parallel_sort(seq.select("pos", "key"), n=n).df.agg(F.count("*").alias("n"), F.max(F.abs(F.col("rnk") - F.col("pos"))).alias("max_displacement"))
    return moved.join(F.broadcast(descents)).select("n", "descents", "max_displacement")


def key_profile(seq: DataFrame) -> DataFrame:
    return pivot_only_lower_bound(seq)


def stage_times(seq: DataFrame, n_blocks: int = 8, n_parts: int = 8) -> dict[str, float]:
    """Seconds of block sort, selection, routing and merge, each from materialised input."""
    from ..operators import blocks, partition, pivots

    kept: list[DataFrame] = []

    def timed(make):
        began = time.perf_counter()
        out = make()
        if isinstance(out, DataFrame):
            out = out.persist()
            kept.append(out)
            out.count()
        return out, time.perf_counter() - began

    blocked, _ = timed(lambda: blocks.assign_blocks(seq, n_blocks))
    _, sort_s = timed(lambda: blocks.sort_blocks(blocked))
    cuts, select_s = timed(lambda: pivots.exact(blocked, n_parts))
    routed, route_s = timed(lambda: partition.route_by_exact_cuts(blocked, cuts))
    order = Window.partitionBy("__id").orderBy("key", "pos")
    placed = routed.withColumn("__id", F.col("part").cast("int")).repartitionById(n_parts, F.col("__id"))
    _, merge_s = timed(lambda: placed.withColumn("at", F.row_number().over(order)))
    for df in kept:
        df.unpersist()
    return {"block_sort": sort_s, "select": select_s, "route": route_s, "merge": merge_s}


def memory(spark: SparkSession, run: Callable[[], DataFrame]) -> dict[str, int]:
    """Bytes that a run shuffles, spills and keeps in execution memory at most, from the
    session's stage metrics.  The sort is not in place: its second copy is the shuffle."""
    context = spark.sparkContext
    store = context._jsc.sc().statusStore()
    none = context._gateway.new_array(context._jvm.double, 0)

    def stages() -> dict[int, object]:
        found = store.stageList(None, False, False, none, None)
        return {(s := found.apply(i)).stageId(): s for i in range(found.size())}

    before = set(stages())
    run().write.format("noop").mode("overwrite").save()
    context._jsc.sc().listenerBus().waitUntilEmpty(10_000)
    own = [s for k, s in stages().items() if k not in before]
    return {
        "shuffle_write": sum(s.shuffleWriteBytes() for s in own),
        "spill_disk": sum(s.diskBytesSpilled() for s in own),
        "peak_execution": max([0, *(s.peakExecutionMemory() for s in own)]),
    }
