"""Experiment drivers: time, efficiency, block sorters, mergers and the claims in shape.

Functions return plain dictionaries for JSON.  Wall-clock figures depend on the machine;
balance figures are deterministic."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import blocks, kernels, partition, pivots, sorter
from .plans import measures
from .sources import workloads

#: Runs of a figure; the study has as many.
RUNS = 20
#: Runs of the drivers of steps, which take four variants of six sequences.
FEW = 3
METHODS = ("exact", "regular", "stable_snap", "native")


def once(make) -> float:
    """Seconds of building and running a DataFrame into nowhere."""
    began = time.perf_counter()
    make().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def mean(make, runs: int = RUNS) -> float:
    """Mean seconds of ``runs`` runs after one that warms up."""
    once(make)
    return sum(once(make) for _ in range(runs)) / runs


def single(seq: DataFrame, method: str) -> float:
    """The one-thread form of a method: one block, one partition."""
    return once(lambda: sorter.parallel_sort(seq, method, 1, 1).df)


def _timed(spark: SparkSession, sf_dir: str, sequences, variants: dict[str, dict], threads: int, runs: int, copies: int) -> dict[str, float]:
    """Mean seconds of each variant of the sort on each sequence with n_B = n_P = threads."""
    out = {}
    for s in sequences:
        seq = workloads.sequence(s, spark, sf_dir)
        seq = (seq if copies == 1 else workloads.amplify(seq.select("pos", "key"), copies)).persist()
        n = seq.count()
        for name, how in variants.items():
            out[f"{name}/{s}"] = mean(lambda how=how, seq=seq, n=n: sorter.parallel_sort(seq, n_blocks=threads, n_parts=threads, n=n, **how).df, runs)
        seq.unpersist()
    return out


def fig_time(spark: SparkSession, sf_dir: str, threads: int, methods=METHODS, sequences=workloads.SEQUENCES, runs: int = RUNS, copies: int = 1, stepwise: bool = False) -> dict[str, float]:
    """Seconds of each method on each sequence.  ``stepwise``: the study's block sorter and
    merger (branchless, tournament; the stable baseline sorts blocks by introsort); else the
    engine's own, which spill."""
    variants = {}
    for m in methods:
        steps = {"block_sort": "intro" if m == "stable_snap" else "branchless", "merge": "tournament"} if stepwise and m != "native" else {}
        variants[m] = {"method": m, **steps}
    return _timed(spark, sf_dir, sequences, variants, threads, runs, copies)


def fig_efficiency(session, sf_dir: str, threads: list[int], methods=("exact", "regular", "stable_snap"), sequences=workloads.SEQUENCES, runs: int = RUNS) -> dict[str, float]:
    """Parallel efficiency T(1) / (t T(t)); ``session(t)`` must start a session on t cores."""
    times: dict[tuple, float] = {}
    for t in threads:
        spark = session(t)
        for key, sec in fig_time(spark, sf_dir, t, methods, sequences, runs).items():
            times[key, t] = sec
        spark.stop()
    return {f"{key}/{t}": times[key, 1] / (t * sec) for (key, t), sec in times.items()}


def fig_block_sorters(spark: SparkSession, sf_dir: str, threads: int, names=("intro", "three_way", "branchless", "spark"), sequences=workloads.SEQUENCES, runs: int = FEW, copies: int = 1) -> dict[str, float]:
    """Seconds of the exact sort with each block sorter under the tournament."""
    return _timed(spark, sf_dir, sequences, {k: {"block_sort": k, "merge": "tournament"} for k in names}, threads, runs, copies)


def fig_mergers(spark: SparkSession, sf_dir: str, threads: int, names=("tournament", "pairs", "binary_heap", "resort"), sequences=workloads.SEQUENCES, runs: int = FEW, copies: int = 1) -> dict[str, float]:
    """Seconds of the exact sort with each merger over introsorted blocks."""
    return _timed(spark, sf_dir, sequences, {m: {"block_sort": "intro", "merge": m} for m in names}, threads, runs, copies)


def kernel_work(n: int = 20_000) -> dict[str, dict]:
    """Counted work of each block sorter on vector forms of the sequences."""
    import numpy as np

    rng = np.random.default_rng(1)
    swapped = np.arange(n)
    at = rng.permutation(n)[: int(n**0.5) // 2 * 2]
    swapped[at[::2]], swapped[at[1::2]] = swapped[at[1::2]], swapped[at[::2]].copy()
    inputs = {"uniform_int": rng.integers(0, 1 << 32, n), "almost_sorted": swapped, "dup3": rng.integers(0, 3, n)}
    out = {}
    for s, keys in inputs.items():
        for k in ("plain_quick", "intro", "branchless", "three_way", "merge_block"):
            stats = kernels.Stats()
            kernels.permutation(k, keys.astype(np.int64), stats)
            out[f"{k}/{s}"] = vars(stats)
    return out


def merger_work(n: int = 20_000, blocks_n: int = 8) -> dict[str, dict]:
    """Counted work of each merger on one partition of n elements from sorted runs of as many
    blocks; a re-sort is counted as introsort of the appended runs."""
    import numpy as np

    rng = np.random.default_rng(2)
    whole = np.arange(n * blocks_n)
    at = rng.permutation(len(whole))[: int(len(whole) ** 0.5) // 2 * 2]
    whole[at[::2]], whole[at[1::2]] = whole[at[1::2]], whole[at[::2]].copy()
    inputs = {"uniform_int": rng.integers(0, 1 << 32, len(whole)), "almost_sorted": whole, "dup3": rng.integers(0, 3, len(whole))}
    out = {}
    for s, keys in inputs.items():
        blocks_ = [np.sort(b) for b in np.array_split(keys, blocks_n)]
        # the middle partition of exact cuts, as every block gives to it
        order = np.argsort(np.concatenate(blocks_), kind="stable")
        part = np.sort(order[len(order) // 2 : len(order) // 2 + n])
        home = part // n
        own = np.concatenate(blocks_)[part]
        runs = [np.flatnonzero(home == b) for b in range(blocks_n)]
        for m in ("tournament", "binary_heap", "resort"):
            stats = kernels.Stats()
            kernels.MERGERS[m](own, runs, stats)
            out[f"{m}/{s}"] = vars(stats)
    return out


def claims(spark: SparkSession, sf_dir: str, threads=(2, 4, 12, 24, 48)) -> dict[str, dict[int, float]]:
    """Merge bounds (N / n_P) / largest partition of the three methods on the three-valued key:
    sampling saturates, exact cuts stay at one, snapped cuts lie between."""
    out: dict[str, dict[int, float]] = {"exact": {}, "regular": {}, "stable_snap": {}}
    seq = workloads.sequence("dup3", spark, sf_dir).select("pos", "key").persist()
    n = seq.count()
    for t in threads:
        own = blocks.assign_blocks(seq, t, n)
        cuts = pivots.exact(own, t, "histogram", n=n)
        routed = {
            "exact": partition.route_by_exact_cuts(own, cuts),
            "regular": partition.route_by_pivots(own, pivots.regular(own, t)),
            "stable_snap": partition.route_by_exact_cuts(own, pivots.stable_snap(own, cuts)),
        }
        for m, rows in routed.items():
            out[m][t] = measures.merge_bound(rows, t).first().bound
    seq.unpersist()
    return out


def native_vs_exact(spark: SparkSession, sf_dir: str, threads: int) -> dict[str, float]:
    """Largest partition over the mean on the three-valued key: the engine's own range
    partitioning against exact cuts."""
    seq = workloads.sequence("dup3", spark, sf_dir).select("pos", "key")
    sizes = {m: sorter.parallel_sort(seq, m, threads, threads).df.groupBy("part").count().agg(F.max("count")).first()[0] for m in ("native", "exact")}
    n = seq.count()
    return {m: v * threads / n for m, v in sizes.items()}
