"""The full sort: blocks, pivots or cuts, one shuffle, merge, global ranks."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.keys import READ, By, held, ordered_long, settled, sort_key
from . import kernels, pivots
from .blocks import assign_blocks, sort_blocks
from .partition import last_places, offsets, route_by_exact_cuts, route_by_pivots

#: Rows of a block or partition where their number isn't given.
ROWS = 2_000_000
METHODS = ("exact", "regular", "random_sample", "stable_snap", "native")


@dataclass
class SortedFrame:
    """A sorted layout: ``df`` has part (its partition) and rnk (global 0-based rank).

    Catalyst can't see that partitions are ranges: stay on ``part`` instead of ordering
    again by the key.  ``inner`` has the column ``__id`` too, by which the rows were shuffled:
    windows and groups on it need no further shuffle."""

    df: DataFrame
    n: int
    n_parts: int
    method: str
    cuts: list = field(default_factory=list)
    work: pivots.Work = field(default_factory=pivots.Work)
    #: The sort of the routed rows in a range of parts, where that needs no other part.
    of_parts: Callable[[int, int], DataFrame] | None = None
    inner: DataFrame | None = None

    def laid(self) -> DataFrame:
        inner = self.df if self.inner is None else self.inner
        return inner if "__id" in inner.columns else inner.withColumn("__id", F.col("part").cast("int"))

    def parts(self, first: int, last: int) -> DataFrame:
        """The rows of parts first..last; other rows are left before the shuffle."""
        if self.of_parts is None:
            return self.df.where(F.col("part").between(first, last))
        return self.of_parts(first, last)


def sequence(df: DataFrame, by: Sequence[By | str], pos: str | None = None) -> DataFrame:
    """``df`` with ``pos`` and ``key``; pos is an existing dense column, or the row's place
    in the scan (files and rows in them), shifted by the counts of the partitions before."""
    keyed = df.withColumn("key", sort_key(df, by))
    if pos is not None:
        return keyed.withColumn("pos", F.col(pos).cast("bigint"))
    marked = keyed.withColumn("__part", F.spark_partition_id()).withColumn("__id", F.monotonically_increasing_id())
    sizes = {r["__part"]: r["n"] for r in marked.groupBy("__part").agg(F.count("*").alias("n")).collect()}
    base, starts = 0, []
    for p in sorted(sizes):
        starts += [F.lit(p), F.lit(base)]
        base += sizes[p]
    if not starts:
        return marked.withColumn("pos", F.lit(0).cast("bigint")).drop("__part", "__id")
    # the low 33 bits of the id count rows inside a partition
    place = F.element_at(F.create_map(*starts), F.col("__part")) + F.col("__id").bitwiseAND(F.lit((1 << 33) - 1))
    return marked.withColumn("pos", place.cast("bigint")).drop("__part", "__id")


def parallel_sort(
    seq: DataFrame, method: str = "exact", n_blocks: int | None = None, n_parts: int | None = None, block_sort: str = "spark",
    merge: str = "resort", strategy: str = "auto", rate: float | None = None, seed: int = 0, n: int | None = None,
) -> SortedFrame:
    """Sort ``seq`` (pos, key, ...) into ``n_parts`` partitions with global ranks, stably.

    Blocks and partitions that aren't given follow from the number of rows."""
    if method not in METHODS:
        raise ValueError(f"unknown method {method}")
    n = seq.count() if n is None else n
    n_blocks, n_parts = (max(8, -(-n // ROWS)) if x is None else x for x in (n_blocks, n_parts))
    work = pivots.Work()
    if method == "native":
        laid = seq.repartitionByRange(n_parts, "key").withColumn("part", F.spark_partition_id().cast("bigint"))
        laid = laid.persist()  # range bounds come from a sample: ranks and offsets must see the same
        return _frame(_ranked(laid, offsets(laid, n_parts)), n, n_parts, method)
    blocked = assign_blocks(seq, n_blocks, n)
    cuts: list = []
    # the defaults sort in the JVM, which spills: a partition's rows once, after the shuffle.  A named
    # kernel or merger goes the four steps: idx, a row's place in its sorted block, travels along
    stepwise = block_sort != "spark" or merge != "resort"
    ordered = sort_blocks(blocked, block_sort) if stepwise else blocked
    if method == "regular":
        cuts = pivots.regular(blocked, n_parts, work=work)
        routed = route_by_pivots(ordered, cuts)
    elif method == "random_sample":
        cuts = pivots.random_sample(blocked, n_parts, rate, seed, work)
        routed = route_by_pivots(ordered, cuts)
    else:
        cuts = pivots.exact(blocked, n_parts, strategy, work, n)
        if method == "stable_snap":
            cuts = pivots.stable_snap(blocked, cuts)
        routed = route_by_exact_cuts(ordered, cuts, places=last_places(blocked, cuts))
    placed = place(routed, n_parts)
    if stepwise:
        placed = merge_partitions(placed, merge)
    if method == "exact":
        # the cuts' ranks are the offsets, known before the shuffle
        start = F.expr(f"(part * {n} + {n_parts - 1}) div {n_parts}")

        def of_parts(first: int, last: int) -> DataFrame:
            own = settled(routed).where(held(F.col("part").between(first, last))).drop(READ)
            return _local(place(own, n_parts), False, start).drop("__id")

        return _frame(_local(placed, stepwise, start), n, n_parts, method, cuts, work, None if stepwise else of_parts)
    # sizes don't hang on the order inside blocks
    sizes = offsets(routed if not stepwise else _reroute(blocked, method, cuts), n_parts)
    return _frame(_ranked(placed, sizes, stepwise), n, n_parts, method, cuts, work)


def _reroute(blocked: DataFrame, method: str, cuts: list) -> DataFrame:
    return route_by_exact_cuts(blocked, cuts) if method == "stable_snap" else route_by_pivots(blocked, cuts)


def _frame(inner: DataFrame, *rest) -> SortedFrame:
    return SortedFrame(inner.drop("__id"), *rest, inner=inner)


def place(routed: DataFrame, n_parts: int) -> DataFrame:
    """The one shuffle of all rows, by partition number.  Grouping by ``__id``, the very column
    it was placed by, needs no further one; by an equal column of another type it would."""
    return routed.withColumn("__id", F.col("part").cast("int")).repartitionById(n_parts, F.col("__id"))


def _local(placed: DataFrame, merged: bool, start) -> DataFrame:
    group = "__id" if "__id" in placed.columns else "part"
    at = F.col("__at") if merged else F.row_number().over(Window.partitionBy(group).orderBy("key", "pos")) - 1
    out = placed.withColumn("rnk", (at + start).cast("bigint"))
    return out.drop("__at", "block")


def _ranked(placed: DataFrame, starts: DataFrame, merged: bool = False) -> DataFrame:
    s = starts.select(F.col("part").alias("__p"), F.col("part_offset").alias("__start"))
    # one row a partition
    joined = placed.join(F.broadcast(s), F.col("part") == F.col("__p")).drop("__p")
    return _local(joined, merged, F.col("__start")).drop("__start")


def merge_partitions(placed: DataFrame, merger: str) -> DataFrame:
    """``placed`` with ``__at``, each row's place in its partition, by a merger of block runs.

    A shuffle does not keep the order inside blocks; ``idx``, the row's place in its sorted
    block, puts every run back.  The merger gets the runs as the block sorter left them: one
    that is not in order fails the sort.  A partition has to fit a worker; the default
    (block sort ``spark``, merge ``resort``) spills instead."""
    if merger not in kernels.MERGERS:
        raise ValueError(f"unknown merger {merger}")
    coded = placed.withColumn("code", ordered_long(F.col("key"), placed.schema["key"].dataType))
    names = [c for c in placed.columns if c != "idx"]
    schema = placed.select(*names).withColumn("__at", F.lit(0).cast("bigint")).schema

    def run(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["block", "idx"], kind="stable").reset_index(drop=True)
        # no code: a null key, which is the smallest
        codes = part["code"].fillna(-(1 << 63)).to_numpy(np.int64) if part["code"].hasnans else part["code"].to_numpy(np.int64)
        block = part["block"].to_numpy(np.int64)
        edges = np.flatnonzero(np.r_[True, block[1:] != block[:-1], True])
        if ((codes[1:] < codes[:-1]) & (block[1:] == block[:-1])).any():
            raise ValueError("a block's run is not sorted")
        runs = [np.arange(a, b) for a, b in zip(edges, edges[1:])]
        out = part.iloc[kernels.MERGERS[merger](codes, runs)][names].copy()
        out["__at"] = np.arange(len(out), dtype=np.int64)
        return out

    return coded.groupBy("__id").applyInPandas(run, schema)


def argsort(seq: DataFrame, **how) -> DataFrame:
    """(rnk, pos): the permutation that sorts the sequence."""
    return parallel_sort(seq.select("pos", "key"), **how).df.select("rnk", "pos")


def two_level(seq: DataFrame, n_parts: int, n_blocks: int = 8, n: int | None = None) -> SortedFrame:
    """Exact splitting in two levels of about sqrt(n_P) cuts: super-partitions first, then the
    cuts inside all of them in one selection.  Ranks and partitions equal the one-level result."""
    n = seq.count() if n is None else n
    outer = max(1, int(n_parts**0.5))
    while n_parts % outer:
        outer -= 1
    blocked = assign_blocks(seq, n_blocks, n)
    coarse = pivots.exact(blocked, outer, n=n)
    ranks = pivots.target_ranks(n, n_parts)
    known = {c.rank: c for c in coarse}
    fine = {c.rank: c for c in pivots.exact(blocked, n_parts, n=n, ranks=sorted(set(ranks) - known.keys()))}
    cuts = [(known.get(r) or fine[r]) for r in ranks] if n else []
    placed = place(route_by_exact_cuts(blocked, cuts), n_parts)
    start = F.expr(f"(part * {n} + {n_parts - 1}) div {n_parts}")
    return _frame(_local(placed, False, start), n, n_parts, "exact", cuts)


def parallel_quick(seq: DataFrame, depth: int = 3, n_blocks: int = 8, n: int | None = None) -> SortedFrame:
    """Parallel quicksort as repeated exact two-way splits: 2^depth partitions.

    All pieces of a level are split by one selection, so there are ``depth`` of them."""
    n = seq.count() if n is None else n
    blocked = assign_blocks(seq, n_blocks, n)
    bounds, cuts = [0, n], []
    for _ in range(depth):
        halves = [a + -(-(b - a) // 2) for a, b in zip(bounds, bounds[1:])]
        cuts += pivots.exact(blocked, 2, n=n, ranks=[h for h, a, b in zip(halves, bounds, bounds[1:]) if a < h < b])
        bounds = sorted(bounds + halves)
    cuts = sorted({c.rank: c for c in cuts}.values(), key=lambda c: c.rank)
    placed = place(route_by_exact_cuts(blocked, cuts), 1 << depth)
    starts = blocked.sparkSession.createDataFrame([(i, r) for i, r in enumerate([0, *(c.rank for c in cuts)])], "part bigint, part_offset bigint")
    return _frame(_ranked(placed, starts), n, 1 << depth, "exact", cuts)
