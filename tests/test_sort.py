import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from evensort.functions.keys import By, literal, ordered_long, ordered_long_to_u64, sort_key, u64_to_ordered_long
from evensort.operators import blocks, kernels, partition, pivots, range_query, rank, sorter
from evensort.plans import cost, measures

STRATEGIES = ("histogram", "rank_search", "domain_bisect", "multiway_search", "sketch_refine")


def frame(spark, keys, kind="bigint"):
    return spark.createDataFrame(list(enumerate(keys)), f"pos bigint, key {kind}").repartition(3)


def brute_cuts(keys, n_parts):
    order = sorted(keys, key=lambda k: (k is not None, k))
    out = []
    for r in pivots.target_ranks(len(keys), n_parts):
        key = order[r - 1]
        less = sum(k is None if key is not None else 0 for k in keys) + sum(k is not None and key is not None and k < key for k in keys)
        same = sum(k == key if k is not None else key is None for k in keys)
        out.append((key, r - less, less, less + same))
    return out


CASES = [[5, 2, 8, 4, 1, 7], [1, 1, 4, 1, 1, 1], [7] * 40, list(range(50)), list(range(50, 0, -1)), [3], [2, 2, 1] * 15 + [None] * 9]


@pytest.mark.parametrize("strategy", STRATEGIES)
def test_strategies_find_the_same_cuts(spark, strategy):
    for keys in CASES:
        for n_parts in (2, 7):
            own = blocks.assign_blocks(frame(spark, keys), 4)
            got = [(c.key, c.take, c.less, c.less_eq) for c in pivots.exact(own, n_parts, strategy)]
            assert got == brute_cuts(keys, n_parts), (keys, n_parts)


def test_large_histograms_are_summed_in_place(spark, monkeypatch):
    monkeypatch.setattr(pivots, "DRIVER_KEYS", 5)
    keys = [random.Random(1).randrange(200) for _ in range(1000)]
    own = blocks.assign_blocks(frame(spark, keys), 4)
    for strategy in ("histogram", "sketch_refine"):
        assert [(c.key, c.take, c.less, c.less_eq) for c in pivots.exact(own, 9, strategy)] == brute_cuts(keys, 9)


def test_worked_examples(spark):
    own = blocks.assign_blocks(frame(spark, [5, 2, 8, 4, 1, 7]), 2)
    assert pivots.regular(own, 2) == [4]
    dup = blocks.assign_blocks(frame(spark, [1, 1, 4, 1, 1, 1]), 2)
    routed = partition.route_by_pivots(dup, pivots.regular(dup, 2))
    assert [r.n for r in partition.part_sizes(routed, 2).orderBy("part").collect()] == [5, 1]
    cuts = pivots.exact(dup, 2)
    assert [(c.key, c.take) for c in cuts] == [(1, 3)]
    assert [r.quota for r in partition.tie_quotas(dup, cuts).orderBy("block").collect()] == [2, 1]
    even = partition.route_by_exact_cuts(dup, cuts)
    assert [r.n for r in partition.part_sizes(even, 2).orderBy("part").collect()] == [3, 3]


@pytest.mark.parametrize("method", sorter.METHODS)
def test_ranks_are_stable_and_total(spark, method):
    rng = random.Random(2)
    for keys in ([], [4], [1, 2, 3], [rng.randrange(5) for _ in range(200)], [None, 3, None, 1]):
        out = sorter.parallel_sort(frame(spark, keys), method, 5, 8, rate=0.3).df.collect()
        order = sorted(range(len(keys)), key=lambda i: (keys[i] is not None, keys[i] or 0, i))
        assert {r.pos: r.rnk for r in out} == {p: i for i, p in enumerate(order)}
        if method == "exact" and keys:
            assert all(r.part == r.rnk * 8 // len(keys) for r in out)


def test_odd_doubles_keep_sparks_order(spark):
    keys = [float("nan"), -0.0, 0.0, float("inf"), float("-inf"), None, 1.5, -2.0, 5e-324, 1e308]
    own = frame(spark, keys, "double")
    want = {r.pos: i for i, r in enumerate(own.orderBy("key", "pos").collect())}
    assert {r.pos: r.rnk for r in sorter.parallel_sort(own, "exact", 2, 3).df.collect()} == want
    coded = own.where("key is not null").withColumn("code", ordered_long(F.col("key"), own.schema["key"].dataType))
    by_code, by_key = coded.orderBy("code", "pos").collect(), coded.orderBy("key", "pos").collect()
    assert [r.pos for r in by_code] == [r.pos for r in by_key]


def test_times_keep_their_order_in_any_zone(spark):
    zone = spark.conf.get("spark.sql.session.timeZone")
    spark.conf.set("spark.sql.session.timeZone", "Europe/Berlin")
    try:
        texts = ["2024-10-27 01:59:59.5", "2024-10-27 02:30:00", "2024-10-27 03:00:00", "2024-03-31 02:30:00", "2024-03-31 03:00:00", "1969-12-31 23:59:59.999999"]
        rows = spark.createDataFrame(list(enumerate(texts)), "pos bigint, s string")
        own = rows.select("pos", F.col("s").cast("timestamp_ntz").alias("key"))
        coded = own.select("key", ordered_long(F.col("key"), own.schema["key"].dataType).alias("code")).orderBy("key").collect()
        codes = [r.code for r in coded]
        assert codes == sorted(set(codes)) and codes[0] == -1
        for strategy in ("sketch_refine", "multiway_search"):
            assert [str(c.key) for c in pivots.exact(own, 3, strategy)] == [str(coded[1].key), str(coded[3].key)]
    finally:
        spark.conf.set("spark.sql.session.timeZone", zone)


def test_unsigned_and_compound_keys(spark):
    values = [0, 2**63 - 1, 2**63, 2**64 - 1]
    df = spark.createDataFrame([(str(v),) for v in values], "s string").select(F.col("s").cast("decimal(20,0)").alias("u"))
    codes = [r.c for r in df.select(u64_to_ordered_long(F.col("u")).alias("c")).collect()]
    assert codes == sorted(codes) and codes[0] == -(2**63)
    assert [int(r.u) for r in df.select(ordered_long_to_u64(u64_to_ordered_long(F.col("u"))).alias("u")).collect()] == values
    rows = [(i, a, b) for i, (a, b) in enumerate([("x", 1), (None, 2), ("xy", 2), ("é", None), ("x", 3), ("", 0)])]
    t = spark.createDataFrame(rows, "id int, a string, b int")
    by = [By("a", desc=True, nulls_last=True), By("b", nulls_last=True), "id"]
    got = [r.id for r in t.orderBy(sort_key(t, by)).collect()]
    assert got == [r.id for r in t.orderBy(F.desc_nulls_last("a"), F.asc_nulls_last("b"), "id").collect()]
    with pytest.raises(ValueError):
        sort_key(t, ["none"])
    assert t.where(F.col("a") == literal("x", t.schema["a"].dataType)).count() == 2


def test_snapped_cuts_never_divide_a_block_run(spark):
    rng = random.Random(3)
    own = blocks.assign_blocks(frame(spark, [rng.randrange(3) for _ in range(120)]), 6)
    cuts = pivots.stable_snap(own, pivots.exact(own, 8))
    pieces = partition.route_by_exact_cuts(own, cuts).groupBy("key", "block").agg(F.countDistinct("part").alias("parts"))
    assert pieces.agg(F.max("parts")).first()[0] == 1


def test_exact_is_balanced_where_sampling_is_not(spark):
    keys = [i % 3 for i in range(480)]
    own = blocks.assign_blocks(frame(spark, keys), 12)
    exact = measures.balance(partition.route_by_exact_cuts(own, pivots.exact(own, 12)), 12).first()
    regular = measures.balance(partition.route_by_pivots(own, pivots.regular(own, 12)), 12).first()
    assert exact.max_n - exact.min_n <= 1 and regular.max_n >= 160 and regular.min_n == 0
    bound = measures.pivot_only_lower_bound(own).first()
    assert bound.top_count <= regular.max_n


def test_two_level_and_quick_equal_one_level(spark):
    rng = random.Random(4)
    keys = [rng.randrange(6) for _ in range(101)]
    own = frame(spark, keys)
    want = {(r.pos, r.part, r.rnk) for r in sorter.parallel_sort(own, "exact", 4, 6).df.collect()}
    assert {(r.pos, r.part, r.rnk) for r in sorter.two_level(own, 6, 4).df.collect()} == want
    assert {(r.pos, r.rnk) for r in sorter.parallel_quick(own, 2, 4).df.collect()} == {(p, k) for p, _, k in want}


def test_search_rounds_stay_logarithmic(spark):
    own = blocks.assign_blocks(frame(spark, [random.Random(5).randrange(10**6) for _ in range(2000)]), 5)
    work = pivots.Work()
    pivots.exact(own, 6, "rank_search", work)
    assert work.rounds <= np.ceil(np.log(2000) / np.log(4 / 3)) + 2
    work = pivots.Work()
    pivots.exact(own, 6, "domain_bisect", work)
    assert work.rounds <= 21


def test_pages_ranges_quantiles_and_scan_positions(spark):
    keys = [random.Random(6).randrange(1000) for _ in range(300)]
    s = sorter.parallel_sort(frame(spark, keys), "exact", 4, 10)
    assert sorted(r.key for r in rank.slice(s, 20, 39).collect()) == sorted(keys)[20:40]
    assert sorted(r.key for r in rank.top_k(s, 7).collect()) == sorted(keys)[:7]
    assert sorted(r.key for r in range_query.between(s, 100, 300).collect()) == sorted(k for k in keys if 100 <= k <= 300)
    assert rank.exact_quantiles(frame(spark, keys), [0.5, 0.99]) == [sorted(keys)[149], sorted(keys)[296]]
    placed = sorter.sequence(spark.range(40).repartition(5), ["id"])
    assert sorted(r.pos for r in placed.collect()) == list(range(40))


def test_one_full_shuffle_and_no_single_partition(spark):
    own = frame(spark, [i * 7919 % 1000 for i in range(400)])
    plan = cost.executed(sorter.parallel_sort(own, "exact", 4, 8, n=400).df.select("pos", "rnk"))
    assert "SinglePartition" not in plan
    assert plan.lower().count("shufflepartitionidpassthrough") == 1
    assert cost.choose(own, 8)[0] in ("regular", "exact") and cost.choose(own, 8, ranks=False)[0] == "native"


def test_dividing_a_key_adds_no_shuffle_of_rows(spark):
    own = frame(spark, [i % 3 for i in range(400)])
    plan = cost.executed(sorter.parallel_sort(own, "exact", 4, 8, n=400).df.select("pos", "rnk")).lower()
    assert plan.count("shufflepartitionidpassthrough") == 1
    assert "exchange hashpartitioning" not in plan and "join" not in plan


@pytest.mark.parametrize("leaf,pieces", [(1, 2), (3, 4), (20_000, 1024)])
def test_places_of_the_last_copies(spark, leaf, pieces):
    rng = random.Random(8)
    for keys in ([rng.randrange(3) for _ in range(200)], [None, 1] * 40, [5] * 64, list(range(30)), [rng.choice("ab\u00e9") for _ in range(90)]):
        own = blocks.assign_blocks(frame(spark, keys, "string" if "a" in keys else "bigint"), 5)
        cuts = pivots.exact(own, 7)
        got = partition.last_places(own, cuts, leaf, pieces)
        for c, place in zip(cuts, got):
            at = [i for i, k in enumerate(keys) if k == c.key]
            assert place == (partition.EVERYWHERE if c.take == len(at) else at[c.take - 1])


# ---- kernels ----


@pytest.mark.parametrize("name", list(kernels.SORTERS))
def test_kernels_give_the_stable_permutation(name):
    rng = np.random.default_rng(1)
    for keys in (rng.integers(0, 3, 500), rng.integers(-(2**62), 2**62, 777), np.arange(100), np.arange(100)[::-1], np.zeros(50, np.int64), np.zeros(0, np.int64)):
        assert (kernels.permutation(name, keys.astype(np.int64)) == np.argsort(keys, kind="stable")).all()


@pytest.mark.parametrize("name", list(kernels.MERGERS))
def test_mergers_are_stable(name):
    rng = np.random.default_rng(2)
    for runs_n in (0, 1, 2, 5, 9):
        runs, at = [], 0
        keys = rng.integers(0, 9, 40 * max(1, runs_n))
        for _ in range(runs_n):
            size = int(rng.integers(0, 40))
            own = np.arange(at, at + size)
            runs.append(own[np.argsort(keys[own], kind="stable")])
            at += size
        got = kernels.MERGERS[name](keys, runs)
        assert (got == np.argsort(keys[:at], kind="stable")).all()


def test_cost_laws():
    rng = np.random.default_rng(3)
    few, n = rng.integers(0, 3, 20_000), 20_000
    s = kernels.Stats()
    kernels.three_way(few, s)
    assert s.comparisons <= 2 * n * 3 + 1000
    s = kernels.Stats()
    kernels.branchless(rng.permutation(n), s)
    assert s.branches < s.comparisons
    killer = np.concatenate([np.arange(0, 4096, 2), np.arange(1, 4096, 2)[::-1]])
    for sort in (kernels.intro, kernels.three_way):
        s = kernels.Stats()
        sort(killer, s)
        assert s.depth <= 2 * 12 + 1 or s.fallbacks
    runs = [np.arange(i, 4000, 8) for i in range(8)]
    s = kernels.Stats()
    kernels.merge_tournament(np.arange(4000), runs, s)
    assert s.comparisons <= 4000 * 3 + 8


def test_classifier_equals_binary_search():
    rng = np.random.default_rng(4)
    keys = rng.integers(0, 100, 1000)
    for m in (0, 1, 2, 5, 15, 16):
        splitters = np.sort(rng.integers(0, 100, m))
        assert (kernels.classify(keys, splitters) == np.searchsorted(splitters, keys, side="left")).all()


# ---- the four steps ----


@pytest.mark.parametrize("block_sort", ["plain_quick", "intro", "branchless", "three_way", "merge_block", "radix", "spark"])
@pytest.mark.parametrize("merge", ["tournament", "pairs", "binary_heap"])
def test_block_sort_and_merge_make_the_sort(spark, block_sort, merge):
    rng = random.Random(11)
    keys = [rng.randrange(40) for _ in range(500)] + [None, None]
    own = frame(spark, keys)
    order = sorted(range(len(keys)), key=lambda i: (keys[i] is not None, keys[i] or 0, i))
    for method in ("exact", "regular"):
        out = sorter.parallel_sort(own, method, 5, 4, block_sort, merge).df
        assert set(out.columns) == {"pos", "key", "part", "rnk"}
        assert {r.pos: r.rnk for r in out.collect()} == {p: i for i, p in enumerate(order)}


def test_a_broken_block_sorter_fails_the_sort(spark, monkeypatch):
    own = frame(spark, [i * 7919 % 1000 for i in range(400)])
    whole = blocks.sort_blocks

    def broken(blocked, kernel="spark"):
        return whole(blocked, kernel).withColumn("idx", 10**6 - F.col("idx"))

    monkeypatch.setattr(sorter, "sort_blocks", broken)
    for merge in ("tournament", "resort", "pairs"):
        with pytest.raises(Exception, match="not sorted"):
            sorter.parallel_sort(own, "exact", 4, 4, "intro", merge).df.collect()


def test_order_of_equal_keys_alone_is_restored():
    keys = np.array([3, 1, 2, 1])
    assert kernels._restored(keys, np.array([3, 1, 2, 0])).tolist() == [1, 3, 2, 0]
    assert kernels._restored(keys, np.array([0, 2, 3, 1])).tolist() == [0, 2, 1, 3]


def test_bad_partitions_have_a_budget_a_path(monkeypatch):
    rng = np.random.default_rng(6)
    for n in (20_000, 100_000):
        s = kernels.Stats()
        kernels.three_way(rng.integers(0, 1 << 32, n), s)
        assert s.fallbacks == 0 and s.comparisons < 2.6 * n * np.log2(n)
    # a pivot that is always the smallest: the whole path goes bad, and stops at floor(log2 N)
    monkeypatch.setattr(kernels, "_middle", lambda v, s: int(np.argmin(v)))
    s, keys = kernels.Stats(), rng.permutation(4096)
    assert (kernels.permutation("three_way", keys, s) == np.argsort(keys)).all()
    assert (s.bad_partitions, s.fallbacks, s.depth) == (12, 1, 13)
    s = kernels.Stats()
    kernels.permutation("intro", keys, s)
    assert s.fallbacks >= 1 and s.depth <= 25


def naive_insertion(v):
    v, compared, moved = list(v), 0, 0
    for i in range(1, len(v)):
        j, x = i, v[i]
        while j:
            compared += 1
            if v[j - 1] <= x:
                break
            v[j], j, moved = v[j - 1], j - 1, moved + 1
        v[j] = x
    return compared, moved


def test_counts_are_those_of_the_element_wise_forms():
    rng = np.random.default_rng(7)
    for _ in range(50):
        v = rng.integers(0, 8, rng.integers(0, 16))
        s = kernels.Stats()
        kernels._insert_all(v.copy(), np.arange(len(v)), [(0, len(v))], s)
        assert (s.comparisons, s.moves) == naive_insertion(v)
    for _ in range(50):
        a, b = (np.sort(rng.integers(0, 9, rng.integers(0, 12))) for _ in range(2))
        s = kernels.Stats()
        kernels._merge_two(np.r_[a, b], np.arange(len(a)), np.arange(len(a), len(a) + len(b)), s)
        i = j = compared = 0
        while i < len(a) and j < len(b):
            compared += 1
            i, j = (i + 1, j) if a[i] <= b[j] else (i, j + 1)
        assert s.comparisons == compared


def test_block_partitioning_exchanges_what_a_scan_finds():
    rng = np.random.default_rng(8)
    for n in (1, 200, 257, 1000, 5000):
        for high in (3, 10**6):
            v = rng.integers(0, high, n)
            pivot = v[rng.integers(0, n)]
            for part in (kernels._by_blocks, kernels._scan_from_both_ends):
                s, own, at = kernels.Stats(), v.copy(), np.arange(n)
                cut = part(own, at, pivot, s)
                assert (own == v[at]).all() and (own[:cut] <= pivot).all() and (own[cut:] >= pivot).all()
                assert n <= s.comparisons <= n + 2 * kernels.BLOCK + 2
    # block partitioning has a branch a block, not an element
    s = kernels.Stats()
    kernels._by_blocks(rng.integers(0, 10**6, 100_000), np.arange(100_000), 500_000, s)
    assert s.branches < 2 * 100_000 / kernels.BLOCK + 4


def test_descending_smallest_long(spark):
    rows = spark.createDataFrame([(0, -(2**63)), (1, 2**63 - 1), (2, None), (3, 0)], "id int, a bigint")
    got = [r.id for r in rows.orderBy(sort_key(rows, [By("a", desc=True, nulls_last=True)])).collect()]
    assert got == [1, 3, 0, 2]


# ---- many cuts ----


def test_counts_in_sorted_arrays_equal_search(spark):
    rng = random.Random(21)
    kinds = {"bigint": lambda: rng.randrange(-50, 50), "double": lambda: rng.choice([rng.random(), float("inf"), float("-inf"), -0.0]), "string": lambda: rng.choice("abé\"\\") * rng.randrange(4)}
    for kind, make in kinds.items():
        keys, bounds = [make() for _ in range(300)], sorted({make() for _ in range(400)} | {0} if kind == "bigint" else {make() for _ in range(400)})
        bounds = sorted(bounds * 90)[: max(65, len(bounds) * 90)]
        own = frame(spark, keys, kind)
        from evensort.functions.keys import with_count

        for strict in (True, False):
            got = {r.pos: r.c for r in with_count(own, "c", F.col("key"), bounds, own.schema["key"].dataType, strict).collect()}
            assert all(got[i] == sum(b < k or (not strict and b == k) for b in bounds) for i, k in enumerate(keys))


@pytest.mark.parametrize("kind", ["bigint", "double", "string", "date", "timestamp_ntz"])
def test_hundreds_of_cuts_equal_brute_force(spark, kind):
    rng = random.Random(22)
    raw = [rng.choice([None, rng.randrange(10**6), rng.randrange(50)]) for _ in range(900)]
    own = frame(spark, raw)
    casts = {"bigint": F.col("key"), "double": F.col("key") / 7, "string": F.col("key").cast("string"), "date": F.date_add(F.lit("2000-01-01"), F.col("key").cast("int") % 9999), "timestamp_ntz": F.timestamp_seconds("key").cast("timestamp_ntz")}
    own = blocks.assign_blocks(own.withColumn("key", casts[kind]), 5).persist()
    keys = [r.key for r in own.orderBy("pos").collect()]
    for strategy in ("auto", "sketch_refine", "multiway_search") if kind != "string" else ("auto", "sketch_refine"):
        got = [(c.key, c.take, c.less, c.less_eq) for c in pivots.exact(own, 300, strategy)]
        assert got == brute_cuts(keys, 300), strategy
    routed = partition.route_by_exact_cuts(own, pivots.exact(own, 300))
    some = next(k for k in keys if k is not None)
    order = sorted(range(900), key=lambda i: (keys[i] is not None, some if keys[i] is None else keys[i], i))
    assert {r.pos: r.part for r in routed.collect()} == {p: i * 300 // 900 for i, p in enumerate(order)}
    own.unpersist()


def test_widest_codes_and_few_pieces(spark):
    keys = [-(2**63), 2**63 - 1, 0, -1, 1, 5, 5, 5, 2**62, -(2**62), None]
    own = blocks.assign_blocks(frame(spark, keys), 3)
    for pieces in (2, 3, 1 << 16):
        got = [(c.key, c.take, c.less, c.less_eq) for c in pivots.exact(own, 6, "multiway_search", pieces=pieces)]
        assert got == brute_cuts(keys, 6)


def test_samples_need_not_reach_the_driver(spark, monkeypatch):
    own = blocks.assign_blocks(frame(spark, [i * 7919 % 1000 for i in range(600)]), 6)
    want = pivots.regular(own, 9)
    monkeypatch.setattr(pivots, "DRIVER_SAMPLES", 3)
    assert pivots.regular(own, 9) == want
    few, many = pivots.Work(), pivots.Work()
    pivots.random_sample(own, 4, work=many)
    pivots.random_sample(own, 16, work=few)
    assert 2 < many.samples / few.samples < 8


def test_blocks_and_parts_follow_the_rows(spark, monkeypatch):
    monkeypatch.setattr(sorter, "ROWS", 20)
    assert sorter.parallel_sort(frame(spark, list(range(400)))).n_parts == 20


# ---- layouts ----


def exchanges(df):
    df.collect()
    plan = df._jdf.queryExecution().executedPlan().toString().split("+- == Initial Plan ==")[0]
    full = [line for line in plan.splitlines() if "Exchange shufflepartitionid" in line and "ReusedExchange" not in line]
    return len(full), sum("Exchange hash" in line for line in plan.splitlines()), plan.count("Scan")


def test_one_full_shuffle_serves_layout_functions(spark):
    from evensort.operators import aggregates, windows

    own = frame(spark, [i * 7919 % 100 for i in range(400)])
    s = sorter.parallel_sort(own, "exact", 4, 8)
    for made in (windows.dense_rank(s), windows.running_sum(s, F.col("key")), windows.lag(s, "pos"), aggregates.distinct_by_sort(s)):
        assert exchanges(made)[:2] == (1, 0)
    # the runs that cross parts, not rows, are grouped by key again
    assert exchanges(aggregates.sorted_group_counts(s))[:2] == (1, 1)


def test_untouched_parts_are_not_shuffled(spark):
    # a source without a shuffle of its own
    own = spark.range(20_000).selectExpr("id AS pos", "id * 7919 % 100003 AS key")
    s = sorter.parallel_sort(own, "exact", 4, 8)
    for made in (rank.slice(s, 60, 90), rank.top_k(s, 30), range_query.between(s, 100, 5000)):
        plan = cost.executed(made)
        shuffle = plan.index("shufflepartitionidpassthrough")
        # the filter on parts stands below the shuffle
        assert "part#" in plan[shuffle:] and "Filter" in plan[shuffle:]
    written = lambda df: measures.memory(spark, lambda: df)["shuffle_write"]
    assert written(rank.top_k(s, 30)) < written(s.df) / 3
