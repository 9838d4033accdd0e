"""Step 3: routing rows to partitions by pivots or by exact cuts; sizes and offsets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.keys import READ, count_bounds, held, literal, settled, with_count
from .pivots import Cut


def route_by_pivots(df: DataFrame, pivots: list) -> DataFrame:
    """``part`` = number of pivots strictly below the key: equal keys stay together."""
    kind = df.schema["key"].dataType
    wrapped = T.StructType([T.StructField("key", kind)])
    return with_count(df, "part", F.struct(F.col("key")), [{"key": p} for p in pivots], wrapped)


def _is_pivot(df: DataFrame, cuts: list[Cut]):
    kind = df.schema["key"].dataType
    distinct = list(dict.fromkeys(repr(c.key) for c in cuts))
    first = {repr(c.key): c.key for c in cuts}
    keys = [literal(first[d], kind) for d in distinct]
    if len(keys) <= 8:
        test = F.lit(False)
        for p in keys:
            test = test | F.col("key").eqNullSafe(p)
        return test
    # a tree of comparisons would not help: the optimizer turns the plain case into a set
    plain = [p for d, p in zip(distinct, keys) if first[d] is not None]
    return F.coalesce(F.col("key").isin(*plain), F.lit(False)) | (F.col("key").isNull() & F.lit(len(plain) < len(keys)))


def equal_counts(blocked: DataFrame, cuts: list[Cut]) -> DataFrame:
    """(key, block, n, low, high) of the rows whose key is a pivot, with their first and last
    position: n_B rows a distinct pivot at most."""
    ties = settled(blocked).where(held(_is_pivot(blocked, cuts)))
    return ties.groupBy("key", "block").agg(F.count("*").alias("n"), F.min("pos").alias("low"), F.max("pos").alias("high"))


def cut_runs(blocked: DataFrame, cuts: list[Cut]) -> DataFrame:
    """(i, take, block, n, low, high, before): for every cut the blocks' runs of its key, with
    the copies in the blocks before.  Stays in the engine: n_B rows a cut."""
    before = Window.partitionBy("key").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    runs = equal_counts(blocked, cuts).withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0)))
    asked = _asked(blocked, [(i, c.key, c.take) for i, c in enumerate(cuts)], "take")
    return runs.join(F.broadcast(asked), F.col("key").eqNullSafe(F.col("__k"))).drop("key", "__k")


def _asked(df: DataFrame, rows: list[tuple], *names: str) -> DataFrame:
    """A small table (i, __k, longs...) with one row a cut."""
    longs = [T.StructField(c, T.LongType()) for c in names]
    schema = T.StructType([T.StructField("i", T.LongType()), T.StructField("__k", df.schema["key"].dataType), *longs])
    return df.sparkSession.createDataFrame(rows, schema)


#: Places before and behind every position.
NOWHERE, EVERYWHERE = -(1 << 63), (1 << 63) - 1
#: Positions of a cut that one group holds; longer spans are cut into pieces and counted again.
LEAF, PIECES = 20_000, 1024


def last_places(blocked: DataFrame, cuts: list[Cut], leaf: int = LEAF, pieces: int = PIECES) -> list[int]:
    """For each cut (P, c) the position of the c-th copy of P: its last row on the left.

    Only cuts that divide the copies of a key need a search.  The first aggregation finds
    the block that holds the copy, further ones a piece of the block's positions; all open
    cuts go together, and the driver gets one row a cut.  Positions are unique."""
    copies = [c.less_eq - c.less for c in cuts]
    places = [EVERYWHERE if c.take >= m else NOWHERE for c, m in zip(cuts, copies)]
    divided = [i for i, (c, m) in enumerate(zip(cuts, copies)) if 0 < c.take < m]
    if not divided:
        return places
    inside = (F.col("before") < F.col("take")) & (F.col("take") <= F.col("before") + F.col("n"))
    rank = (F.col("take") - F.col("before")).alias("rank")
    found = cut_runs(blocked, [cuts[i] for i in divided]).where(inside).select("i", "block", "low", "high", "n", rank).collect()
    spans = {divided[r.i]: r for r in found}
    own = settled(blocked).where(held(_is_pivot(blocked, [cuts[i] for i in divided]))).select("key", "block", "pos")

    def rows(of: list[int]) -> DataFrame:
        asked = _asked(blocked, [(i, cuts[i].key, r.block, r.low, r.high, r.rank) for i in of for r in [spans[i]]], "__b", "__low", "__high", "take")
        held_by = F.col("key").eqNullSafe(F.col("__k")) & (F.col("block") == F.col("__b")) & F.col("pos").between(F.col("__low"), F.col("__high"))
        return own.join(F.broadcast(asked), held_by)

    while wide := [i for i, r in spans.items() if r.n > leaf and r.low < r.high]:
        width = F.floor((F.col("__high") - F.col("__low")) / pieces) + 1
        piece = F.floor((F.col("pos") - F.col("__low")) / width).alias("piece")
        counts = rows(wide).groupBy("i", "__b", "take", piece).agg(F.count("*").alias("n"), F.min("pos").alias("low"), F.max("pos").alias("high"))
        before = Window.partitionBy("i").orderBy("piece").rowsBetween(Window.unboundedPreceding, -1)
        counts = counts.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0)))
        for r in counts.where(inside).select("i", F.col("__b").alias("block"), "low", "high", "n", rank).collect():
            spans[r.i] = r
    for i, r in spans.items():
        places[i] = r.low
    narrow = [i for i, r in spans.items() if r.low < r.high]
    if narrow:
        at = F.element_at(F.array_sort(F.collect_list("pos")), F.first("take").cast("int"))
        for r in rows(narrow).groupBy("i").agg(at.alias("at")).collect():
            places[r.i] = r["at"]
    return places


def tie_ranks(blocked: DataFrame, cuts: list[Cut]) -> DataFrame:
    """``__tau``: each row's 0-based rank among equal keys, by (block, place in block).

    Only rows equal to a pivot need it.  They are numbered inside (block, key), so a key
    that fills the input is spread over its blocks, and shifted by the counts of the
    blocks before.  All other rows stay where they are.
    """
    before = Window.partitionBy("key").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    base = equal_counts(blocked, cuts).select(F.col("key").alias("__k"), F.col("block").alias("__b"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("__base"))
    own = F.row_number().over(Window.partitionBy("block", "key").orderBy("pos")) - 1
    rows, test = settled(blocked), _is_pivot(blocked, cuts)
    tied = rows.where(held(test)).withColumn("__own", own)
    tied = tied.join(base, F.col("key").eqNullSafe(F.col("__k")) & (F.col("block") == F.col("__b")))
    tied = tied.withColumn("__tau", (F.col("__base") + F.col("__own")).cast("bigint")).select(*blocked.columns, "__tau")
    return tied.unionByName(rows.where(held(~test)).drop(READ).withColumn("__tau", F.lit(0).cast("bigint")))


def route_by_exact_cuts(blocked: DataFrame, cuts: list[Cut], stable: bool = True, salts: int = 64, places: list[int] | None = None) -> DataFrame:
    """``part`` = number of cuts (P, c) that a row lies behind: its key is over P, or it is P
    and at least c copies come before it.

    Stable routing turns c into the position of the c-th copy, so a row is placed by
    comparing its key and position alone: a projection, without a shuffle or join of the
    rows.  Unstable routing numbers ties by salts instead, for input without blocks.
    ``places``: what last_places gives, where known."""
    if not cuts:
        return blocked.withColumn("part", F.lit(0).cast("bigint"))
    kind = blocked.schema["key"].dataType
    if stable:
        places = last_places(blocked, cuts) if places is None else places
        pair = T.StructType([T.StructField("key", kind), T.StructField("__place", T.LongType())])
        x = F.struct(F.col("key"), F.col("pos").cast("bigint").alias("__place"))
        return with_count(blocked, "part", x, [{"key": c.key, "__place": at} for c, at in zip(cuts, places)], pair)
    salted = blocked.drop("block").withColumn("block", F.pmod(F.xxhash64("pos"), F.lit(salts)))
    ranked = tie_ranks(salted, cuts).drop("block")
    bounds = [F.struct(literal(c.key, kind).alias("key"), F.lit(c.take).cast("bigint").alias("__tau")) for c in cuts]
    return ranked.withColumn("part", count_bounds(F.struct("key", "__tau"), bounds, strict=False)).drop("__tau")


def tie_quotas(blocked: DataFrame, cuts: list[Cut]) -> DataFrame:
    """(k, block, quota): copies of P_k that each block gives to the left side, in order."""
    spark = blocked.sparkSession
    counts = equal_counts(blocked, cuts)
    before = Window.partitionBy("key").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0)))
    from .pivots import cuts_frame

    c = cuts_frame(spark, cuts, blocked.schema["key"].dataType).select("k", F.col("pivot_key"), "take")
    quota = F.greatest(F.lit(0), F.least(F.col("n"), F.col("take") - F.col("base"))).cast("bigint")
    return counts.join(F.broadcast(c), F.col("key").eqNullSafe(F.col("pivot_key"))).select("k", "block", quota.alias("quota"))


def piece_sizes(routed: DataFrame) -> DataFrame:
    """(block, part, n): sizes of the pieces that step 4 merges."""
    return routed.groupBy("block", "part").agg(F.count("*").alias("n"))


def part_sizes(routed: DataFrame, n_parts: int) -> DataFrame:
    """(part, n) of all partitions, empty ones included."""
    every = routed.sparkSession.range(n_parts).select(F.col("id").alias("part"))
    return every.join(routed.groupBy("part").agg(F.count("*").alias("n")), "part", "left").select("part", F.coalesce("n", F.lit(0)).alias("n"))


def offsets(routed: DataFrame, n_parts: int) -> DataFrame:
    """(part, n, part_offset): exclusive prefix sums of the sizes, one row a partition.

    The sums are the method's one sequential step; they run over n_P figures."""
    sizes = part_sizes(routed, n_parts)
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    return sizes.withColumn("part_offset", F.coalesce(F.sum("n").over(before), F.lit(0)).cast("bigint"))
