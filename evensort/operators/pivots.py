"""Step 2: pivots by sampling rules, and exact cuts by several search strategies.

An exact cut k of N rows over n_P partitions is (P_k, c_k): P_k is the key of 0-based rank
r_k - 1 with r_k = ceil(k N / n_P), and c_k of its copies belong left of the cut.  Every
strategy finds the same cuts; they differ in passes, driver rounds and memory:

* ``histogram``: one aggregation by key, for few distinct keys;
* ``rank_search``: rounds of weighted medians over sorted blocks, each a binary search;
* ``multiway_search``: several probes a pivot and round over the key's long code;
* ``domain_bisect``: one probe a pivot and round over the long code;
* ``sketch_refine``: quantile sketch, then exact counts around the targets (default).

Nothing here collects more than the cuts, the probes or one figure a partition.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.keys import held, literal, mix32, ordered_long, settled, sorted_array, with_count
from .blocks import sort_blocks


@dataclass(frozen=True)
class Cut:
    k: int
    key: object
    take: int
    rank: int
    less: int
    less_eq: int


@dataclass
class Work:
    """What a selection cost: driver rounds, probes counted, samples taken."""

    rounds: int = 0
    probes: int = 0
    samples: int = 0
    notes: dict = field(default_factory=dict)


def target_ranks(n: int, n_parts: int) -> list[int]:
    return [-(-k * n // n_parts) for k in range(1, n_parts)]


# ---- sampling rules ----


def spaced(sorted_samples: list, n_parts: int) -> list:
    """Pivot k is the sample of 1-based rank ceil(k S / n_P)."""
    s = len(sorted_samples)
    return [sorted_samples[-(-k * s // n_parts) - 1] for k in range(1, n_parts)] if s else []


def regular_samples(blocked: DataFrame, n_parts: int, per_block: int | None = None) -> DataFrame:
    """(block, j, key) at places floor(j m / (s + 1)) of each sorted block of m rows, with
    s = n_P - 1 or the cap ``per_block``."""
    s = n_parts - 1 if per_block is None else min(per_block, n_parts - 1)
    ranked = sort_blocks(blocked)
    sizes = blocked.groupBy("block").agg(F.count("*").alias("m"))
    at = sizes.select(F.col("block").alias("b"), "m", F.explode(F.sequence(F.lit(1), F.lit(s))).alias("j")) if s > 0 else sizes.limit(0).select(F.col("block").alias("b"), "m", F.lit(1).alias("j"))
    at = at.withColumn("place", F.floor(F.col("j") * F.col("m") / (s + 1)).cast("bigint"))
    return ranked.join(at, (F.col("block") == F.col("b")) & (F.col("idx") == F.col("place"))).select("block", "j", "key")


#: Samples that the driver sorts itself.
DRIVER_SAMPLES = 100_000


def regular(blocked: DataFrame, n_parts: int, per_block: int | None = None, work: Work | None = None) -> list:
    """Pivots by regular sampling of sorted blocks.

    Full sampling takes n_B (n_P - 1) keys; ``per_block`` caps them.  Over ``DRIVER_SAMPLES``
    the samples stay in the engine, where the pivots are selected by rank."""
    picked = regular_samples(blocked, n_parts, per_block).select("key")
    small = [r.key for r in picked.limit(DRIVER_SAMPLES + 1).orderBy("key").collect()]
    if work is not None:
        work.samples += len(small)
    return spaced(small, n_parts) if len(small) <= DRIVER_SAMPLES else [c.key for c in exact(picked, n_parts)]


#: Share of the rows that the sampling rule takes on one thread; on t it takes a t-th of it.
ONE_THREAD_RATE = 0.4


def random_sample(df: DataFrame, n_parts: int, rate: float | None = None, seed: int = 0, work: Work | None = None) -> list:
    """Pivots from rows kept by a mix of their position: a portable Bernoulli sample.

    Without a ``rate`` it is ``ONE_THREAD_RATE`` / n_P: the sample grows with N / t.  Pivot k
    is the sample of rank ceil(k S / n_P), selected in the engine: no sample is collected."""
    rate = min(1.0, ONE_THREAD_RATE / n_parts) if rate is None else rate
    kept = df.where(mix32(F.col("pos") + seed) < int(rate * (1 << 32))).select("pos", "key")
    n = kept.count()
    if work is not None:
        work.samples += n
    return [c.key for c in exact(kept, n_parts, n=n)]


# ---- exact cuts ----


def exact(df: DataFrame, n_parts: int, strategy: str = "auto", work: Work | None = None, n: int | None = None, ranks: list[int] | None = None, **how) -> list[Cut]:
    """The cuts of ``df`` (pos, key) for n_P partitions, or for given ranks (1-based)."""
    work = work if work is not None else Work()
    kind = df.schema["key"].dataType
    n = df.count() if n is None else n
    ranks = target_ranks(n, n_parts) if ranks is None else ranks
    if n == 0 or not ranks:
        return []
    if strategy == "auto":
        # a sketch is as good as its size; the multiway search narrows any number of cuts alike
        strategy = "histogram" if not _has_code(kind) else "sketch_refine" if len(ranks) <= SKETCHED else "multiway_search"
    found = {"histogram": _histogram, "rank_search": _rank_search, "sketch_refine": _sketch_refine, "domain_bisect": _bisect, "multiway_search": _multiway}[strategy](df, kind, n, ranks, work, **how)
    return [Cut(k, key, r - less, r, less, less_eq) for k, (r, (key, less, less_eq)) in enumerate(zip(ranks, found), 1)]


#: Cuts up to which a quantile sketch is the default.
SKETCHED = 500


def _has_code(kind: T.DataType) -> bool:
    return isinstance(kind, (T.IntegralType, T.FractionalType, T.DateType, T.TimestampType, T.TimestampNTZType, T.BooleanType)) and not (isinstance(kind, T.DecimalType) and kind.precision > 18)


def running_counts(counts: DataFrame) -> DataFrame:
    """(key, n, less) from (key, n): counts below each key, by range-partitioned two-level
    sums, so that no task sees all keys."""
    return _running_counts(counts)[0]


def _running_counts(counts: DataFrame) -> tuple[DataFrame, DataFrame]:
    # the layout is made once: partition numbers of a later pass must be the same
    cached = counts.repartitionByRange("key").sortWithinPartitions("key").persist()
    laid = cached.withColumn("part", F.spark_partition_id())
    totals = {r.part: r.n for r in laid.groupBy("part").agg(F.sum("n").alias("n")).collect()}
    base, starts = 0, []
    for p in sorted(totals):
        starts += [F.lit(p), F.lit(base)]
        base += totals[p]
    if not starts:
        return laid.select("key", "n", F.lit(0).cast("bigint").alias("less")), cached
    before = Window.partitionBy("part").orderBy("key").rowsBetween(Window.unboundedPreceding, -1)
    own = F.coalesce(F.sum("n").over(before), F.lit(0))
    return laid.select("key", "n", (own + F.element_at(F.create_map(*starts), F.col("part"))).cast("bigint").alias("less")), cached


#: Distinct keys of a histogram that the driver sums itself; larger ones are summed in place.
DRIVER_KEYS = 100_000


def _find(counts: DataFrame, ranks: list[int], base: int = 0) -> dict[int, tuple]:
    """rank -> (key, less, less_eq) from (key, n) of a histogram, ``base`` rows below it."""
    small = counts.limit(DRIVER_KEYS + 1).orderBy("key").collect()
    if len(small) > DRIVER_KEYS:
        summed, cached = _running_counts(counts)
        picked = _pick(summed, ranks, base)
        cached.unpersist()
        return picked
    ends = np.cumsum([r.n for r in small]) + base
    out = {}
    for r in set(ranks):
        i = int(np.searchsorted(ends, r))
        if i < len(small) and r > base:
            out[r] = (small[i].key, int(ends[i]) - small[i].n, int(ends[i]))
    return out


def _pick(summed: DataFrame, ranks: list[int], base: int = 0) -> dict[int, tuple]:
    """rank -> (key, less, less_eq) of rows (key, n, less) that hold a rank."""
    wanted = sorted(set(ranks))
    held_ = _holding(summed.withColumn("less", F.col("less") + base), wanted)
    out = {}
    for row in held_.select("key", "n", "less", "__first", "__end").collect():
        for r in wanted[row["__first"] : row["__end"]]:
            out[r] = (row.key, row.less, row.less + row.n)
    return out


def _holding(summed: DataFrame, wanted: list[int]) -> DataFrame:
    """Rows (n, less, ...) with less < r <= less + n for some of the rising ranks, with the
    places of the first and behind the last of those in the list."""
    counted = with_count(summed, "__first", F.col("less"), wanted, T.LongType(), strict=False)
    counted = with_count(counted, "__end", F.col("less") + F.col("n"), wanted, T.LongType(), strict=False)
    return counted.where("__first < __end")


def _histogram(df, kind, n, ranks, work):
    work.rounds += 1
    found = _find(df.groupBy("key").agg(F.count("*").alias("n")), ranks)
    return [found[r] for r in ranks]


def block_arrays(df: DataFrame) -> DataFrame:
    """One row a block: its keys in order, as an array.  A block must fit a worker."""
    return df.groupBy("block").agg(F.array_sort(F.collect_list("key")).alias("keys"))


def _rank_search(df, kind, n, ranks, work):
    """Each round halves about a quarter to a half of what is left: every block offers the
    middle of its open interval, the driver takes the length-weighted median, and blocks
    count it by binary search.  Both following middles come with the counts, so a round is
    one job.  Nulls, which have no place in the arrays, are counted apart."""
    nulls = df.where("key IS NULL").count()
    arrays = block_arrays(df.where("key IS NOT NULL") if "block" in df.columns else df.where("key IS NOT NULL").withColumn("block", F.spark_partition_id())).persist()
    open_ = {i: (None, None) for i, r in enumerate(ranks) if r > nulls}
    found = {i: (None, 0, nulls) for i, r in enumerate(ranks) if r <= nulls}
    middles = _probe(arrays, {i: (None, None, None) for i in open_}, kind)
    work.rounds += 1
    offers = {i: [(m, w) for m, w in middles[i][2]] for i in open_}
    while open_:
        candidates = {i: _weighted_median(offers[i]) for i in open_}
        got = _probe(arrays, {i: (*open_[i], candidates[i]) for i in open_}, kind)
        work.rounds += 1
        work.probes += len(open_)
        for i in list(open_):
            less, eq, low, high = got[i][0], got[i][1], got[i][2], got[i][3]
            target = ranks[i] - nulls
            if less < target <= less + eq:
                found[i] = (candidates[i], less + nulls, less + eq + nulls)
                del open_[i]
            elif target <= less:
                open_[i], offers[i] = (open_[i][0], candidates[i]), low
            else:
                open_[i], offers[i] = (candidates[i], open_[i][1]), high
    arrays.unpersist()
    return [found[i] for i in range(len(ranks))]


def _weighted_median(offers):
    offers = sorted(offers, key=lambda x: x[0])
    half, seen = sum(w for _, w in offers) / 2, 0
    for m, w in offers:
        seen += w
        if seen >= half:
            return m
    raise ValueError("no offers")


def _searches(keys):
    """A block's keys and its searches for the first place of a value and the one behind its
    last: numbers as they come from Arrow, other keys as a list."""
    if isinstance(keys, np.ndarray) and keys.dtype.kind in "iuf":
        return keys, lambda v: int(np.searchsorted(keys, v, "left")), lambda v: int(np.searchsorted(keys, v, "right"))
    own = list(keys)
    return own, lambda v: bisect_left(own, v), lambda v: bisect_right(own, v)


def _probe(arrays: DataFrame, asks: dict, kind: T.DataType) -> dict:
    """For each ask (low, high, candidate): counts below and equal, and the blocks' middles
    (value, length) of (low, candidate) and (candidate, high); without a candidate only the
    middles of the whole interval."""
    schema = T.StructType(
        [
            T.StructField("i", T.IntegerType()), T.StructField("less", T.LongType()), T.StructField("eq", T.LongType()),
            T.StructField("low", kind), T.StructField("low_n", T.LongType()), T.StructField("high", kind), T.StructField("high_n", T.LongType()),
        ]
    )

    def run(batches):
        for b in batches:
            rows = []
            for keys in b["keys"]:
                keys, left, right = _searches(keys)
                for i, (low, high, cand) in asks.items():
                    lo = right(low) if low is not None else 0
                    hi = left(high) if high is not None else len(keys)
                    if cand is None:
                        rows.append((i, 0, 0, keys[(lo + hi) // 2] if hi > lo else None, hi - lo, None, 0))
                        continue
                    a, z = left(cand), right(cand)
                    down, up = a - lo, hi - z
                    rows.append((i, a, z - a, keys[(lo + a) // 2] if down > 0 else None, max(0, down), keys[(z + hi) // 2] if up > 0 else None, max(0, up)))
            yield pd.DataFrame(rows, columns=[f.name for f in schema.fields]).astype({"i": np.int32}) if rows else pd.DataFrame({f.name: [] for f in schema.fields})

    out: dict = {i: [0, 0, [], []] for i in asks}
    for r in arrays.select("keys").mapInPandas(run, schema).collect():
        out[r.i][0] += r.less
        out[r.i][1] += r.eq
        if r.low_n:
            out[r.i][2].append((r.low, r.low_n))
        if r.high_n:
            out[r.i][3].append((r.high, r.high_n))
    return out


def _coded(df: DataFrame, kind: T.DataType) -> DataFrame:
    if not _has_code(kind):
        raise TypeError(f"{kind.simpleString()} keys have no long code; use histogram, rank_search or sketch_refine")
    return df.select("key", ordered_long(F.col("key"), kind).alias("code"))


def _bisect(df, kind, n, ranks, work, fanout: int = 1):
    """A probe halves each open interval of codes; one aggregation counts the rows under every
    probe, all pivots together."""
    coded = _coded(df, kind).persist()
    lo, hi, nulls = coded.agg(F.min("code"), F.max("code"), F.count_if(F.col("key").isNull())).first()
    found = {i: (None, 0, nulls) for i, r in enumerate(ranks) if r <= nulls}
    # invariant: rows with code <= low are fewer than the rank, rows with code <= high are not
    open_ = {i: [lo - 1, hi] for i, r in enumerate(ranks) if r > nulls}
    while any(high - low > 1 for low, high in open_.values()):
        probes = sorted({low + (high - low) * (j + 1) // (fanout + 1) for low, high in open_.values() if high - low > 1 for j in range(fanout)} - {low for low, _ in open_.values()})
        counts = []
        for at in range(0, len(probes), 400):
            part = probes[at : at + 400]
            counts += list(coded.agg(*[F.count_if(F.col("code") <= F.lit(p)) for p in part]).first())
        work.rounds += 1
        work.probes += len(probes)
        for i, bounds in open_.items():
            for p, c in zip(probes, counts):
                if bounds[0] < p < bounds[1]:
                    if c + nulls < ranks[i]:
                        bounds[0] = p
                    else:
                        bounds[1] = p
                        break
    codes = sorted({high for _, high in open_.values()})
    if codes:
        rows = coded.where(F.col("code").isin(codes)).groupBy("code").agg(F.min("key").alias("key"), F.count("*").alias("n")).collect()
        under = list(coded.agg(*[F.count_if(F.col("code") < F.lit(c)) for c in codes]).first())
        by = {r.code: (r.key, nulls + under[codes.index(r.code)], nulls + under[codes.index(r.code)] + r.n) for r in rows}
        found.update({i: by[high] for i, (_, high) in open_.items()})
    coded.unpersist()
    return [found[i] for i in range(len(ranks))]


#: Groups that a round counts, and pieces of one interval at most.
GROUPS, PIECES = 1 << 20, 1 << 16


def _multiway(df, kind, n, ranks, work, groups: int = GROUPS, pieces: int = PIECES):
    """Open intervals of codes are cut into pieces, the more the fewer are open; a row finds
    its interval in a sorted array, and (interval, piece) is the grouping column of one
    aggregation.  Pieces that hold a rank are the next intervals, shrunk to the codes seen,
    until a piece has one code.  The driver gets one row a rank and round."""
    coded = _coded(df, kind)
    lo, hi, nulls = coded.agg(F.min("code"), F.max("code"), F.count_if(F.col("key").isNull())).first()
    found = {r: (None, 0, nulls) for r in ranks if r <= nulls}
    wanted = sorted({r for r in ranks if r > nulls})
    open_ = [(lo, hi, nulls)] if wanted else []
    whole = coded.where(F.col("key").isNotNull())
    while open_:
        lows, highs, bases = zip(*open_)
        most = max(2, min(pieces, groups // len(open_)))
        # a monotone image keeps the widest intervals inside a long
        shift = int(max(b - a for a, b in zip(lows, highs)) >= 1 << 62)
        widths = [((b >> shift) - (a >> shift)) // most + 1 for a, b in zip(lows, highs)]
        rows = with_count(whole, "i", F.col("code"), lows, T.LongType(), strict=False)
        at = lambda values: F.element_at(sorted_array(values, T.LongType()), F.greatest(F.col("i"), F.lit(1)).cast("int"))
        rows = rows.where((F.col("i") > 0) & (F.col("code") <= at(highs)))
        rows = rows.withColumns({"__low": F.shiftright(at(lows), shift), "__width": at(widths)})
        piece = F.expr(f"(shiftright(code, {shift}) - __low) div __width")
        counts = rows.groupBy("i", piece.alias("piece")).agg(F.count("*").alias("n"), F.min("code").alias("a"), F.max("code").alias("z"), F.min("key").alias("key"))
        before = Window.partitionBy("i").orderBy("piece").rowsBetween(Window.unboundedPreceding, -1)
        summed = counts.withColumn("less", (F.coalesce(F.sum("n").over(before), F.lit(0)) + at(bases)).cast("bigint"))
        work.rounds += 1
        work.probes += len(open_) * most
        open_ = []
        for row in _holding(summed, wanted).select("a", "z", "n", "less", "key", "__first", "__end").orderBy("a").collect():
            if row.a == row.z:
                found.update({r: (row.key, row.less, row.less + row.n) for r in wanted[row["__first"] : row["__end"]]})
            else:
                open_.append((row.a, row.z, row.less))
    return [found[r] for r in ranks]


def _sketch_refine(df, kind, n, ranks, work, eps: float | None = None):
    """Brackets around the targets from a quantile sketch (numbers and times) or a sample of
    rows (other keys), then one exact pass: counts under every bracket and a histogram inside.
    A bracket that misses its target is widened and counted again."""
    eps = eps or 1 / (40 * (len(ranks) + 1))
    known = df.select("key")
    numeric = _has_code(kind) and not isinstance(kind, T.BooleanType)
    reach = 2 * eps if numeric else 4 * eps
    grid = sorted({min(1.0, max(0.0, r / n + d)) for r in ranks for d in (-reach, reach)})
    if numeric:
        sketch = known.agg(F.approx_percentile("key", F.array(*[F.lit(g) for g in grid]), F.lit(int(4 / eps)))).first()[0]
        marks = dict(zip(grid, sketch or []))
    else:
        picked = sorted(known.where(F.col("key").isNotNull()).sample(min(1.0, 8 / (eps * n)), 7).collect(), key=lambda r: r.key)
        work.samples += len(picked)
        marks = {g: picked[min(len(picked) - 1, int(g * len(picked)))].key for g in grid} if picked else {}
    found: dict[int, tuple] = {}
    brackets: list[tuple] = []
    if marks:
        for r in ranks:
            low, high = marks[min(1.0, max(0.0, r / n - reach))], marks[min(1.0, max(0.0, r / n + reach))]
            if brackets and low <= brackets[-1][1]:
                brackets[-1] = (brackets[-1][0], max(brackets[-1][1], high))
            else:
                brackets.append((low, high))
    work.rounds += 1
    # a row lies in a bracket if it has passed one low more than highs; what it has passed is
    # the grouping column of the counts
    passed = known.where(F.col("key").isNotNull())
    passed = with_count(passed, "__lows", F.col("key"), [b[0] for b in brackets], kind, strict=False)
    passed = with_count(passed, "__highs", F.col("key"), [b[1] for b in brackets], kind, strict=True)
    counts = {(r["__lows"], r["__highs"]): r.n for r in passed.groupBy("__lows", "__highs").agg(F.count("*").alias("n")).collect()}
    nulls = n - sum(counts.values())
    found.update({r: (None, 0, nulls) for r in ranks if r <= nulls})
    # brackets are apart and in order, so one histogram over all of them has the running
    # counts; ``shift`` takes a bracket's ranks to ranks among the rows in brackets
    shifts, before, under = [], 0, 0
    for b in range(len(brackets)):
        under += counts.get((b, b), 0)
        size = counts.get((b + 1, b), 0)
        shifts.append((under, size, nulls + under - before))
        before += size
        under += size
    local: dict[int, int] = {}
    starts = [u for u, _, _ in shifts]
    for r in ranks:
        b = bisect_left(starts, r - nulls) - 1
        if r not in found and b >= 0 and r - nulls <= shifts[b][0] + shifts[b][1]:
            local[r] = shifts[b][2]
    if local:
        inside = settled(passed).where(held(F.col("__lows") > F.col("__highs"))).groupBy("key").agg(F.count("*").alias("n"))
        picked_ranks = _find(inside, [r - shift for r, shift in local.items()])
        for r, shift in local.items():
            key, less, less_eq = picked_ranks[r - shift]
            found[r] = (key, less + shift, less_eq + shift)
    work.rounds += 1
    missed = [r for r in ranks if r not in found]
    if missed:
        work.notes["widened"] = len(missed)
        whole = known.groupBy("key").agg(F.count("*").alias("n"))
        found.update(_find(whole, missed))
    return [found[r] for r in ranks]


def stable_snap(blocked: DataFrame, cuts: list[Cut]) -> list[Cut]:
    """Cuts whose quota is rounded down to whole blocks' runs of the key: no block's equal
    keys are divided."""
    from .partition import cut_runs

    if not cuts:
        return []
    end = F.col("before") + F.col("n")
    whole = cut_runs(blocked, cuts).where(end <= F.col("take")).groupBy("i").agg(F.max(end).alias("take")).collect()
    takes = {r.i: r.take for r in whole}
    return [Cut(c.k, c.key, takes.get(i, 0), c.less + takes.get(i, 0), c.less, c.less_eq) for i, c in enumerate(cuts)]


def exact_weighted(df: DataFrame, weight: str, n_parts: int) -> DataFrame:
    """(k, pivot_key, cut_weight, less_weight, key_weight): the keys where the running weight
    reaches ceil(k W / n_P); balances bytes instead of rows."""
    counts = df.groupBy("key").agg(F.sum(weight).cast("bigint").alias("n"))
    total = int(counts.agg(F.sum("n")).first()[0] or 0)
    ranks = target_ranks(total, n_parts)
    found = _find(counts, ranks)
    rows = [(k, found[r][0], r, found[r][1], found[r][2] - found[r][1]) for k, r in enumerate(ranks, 1)]
    key = df.schema["key"].dataType
    schema = T.StructType([T.StructField("k", T.LongType()), T.StructField("pivot_key", key), *[T.StructField(c, T.LongType()) for c in ("cut_weight", "less_weight", "key_weight")]])
    return df.sparkSession.createDataFrame(rows, schema)


def cuts_frame(spark: SparkSession, cuts: list[Cut], kind: T.DataType) -> DataFrame:
    longs = lambda *names: [T.StructField(c, T.LongType()) for c in names]
    schema = T.StructType([*longs("k"), T.StructField("pivot_key", kind), *longs("take", "cut_rank", "less", "less_eq")])
    return spark.createDataFrame([(c.k, c.key, c.take, c.rank, c.less, c.less_eq) for c in cuts], schema)


def pivots_frame(spark: SparkSession, pivots: list, kind: T.DataType) -> DataFrame:
    schema = T.StructType([T.StructField("k", T.LongType()), T.StructField("pivot_key", kind)])
    return spark.createDataFrame([(k, p) for k, p in enumerate(pivots, 1)], schema)


def check_cuts(df: DataFrame, cuts: list[Cut], n_parts: int) -> DataFrame:
    """(k, less, less_eq, holds): counts around each pivot and whether the defining
    inequality less <= k N / n_P <= less_eq holds; one pass over the keys."""
    kind = df.schema["key"].dataType
    x = F.struct(F.col("key"))
    low = lambda c: F.struct(literal(c.key, kind).alias("key"))
    sums = [F.struct(F.lit(c.k).cast("bigint").alias("k"), F.count_if(x < low(c)).alias("less"), F.count_if(x <= low(c)).alias("less_eq")) for c in cuts]
    rows = df.agg(F.count("*").alias("n"), F.array(*sums).alias("x")).select("n", F.explode("x").alias("x"))
    holds = (F.col("x.less") * n_parts <= F.col("x.k") * F.col("n")) & (F.col("x.k") * F.col("n") <= F.col("x.less_eq") * n_parts)
    return rows.select("x.k", "x.less", "x.less_eq", holds.alias("holds"))
