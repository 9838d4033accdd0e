import os

import numpy as np
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from evensort import bench, catalog
from evensort.functions import udfs
from evensort.operators import joins, merge_files, sorter, windows
from evensort.plans import measures
from evensort.sources import generator, io, workloads
from evensort.streaming import streams

SF = "/root/testdata/sf0.001"


def test_every_oracle_has_a_query():
    assert set(catalog.oracles()) <= set(catalog.queries())


def test_generated_sequences(spark):
    generator.register(spark)
    for kind in ("uniform_int", "uniform_float", "dup3", "sorted"):
        rows = spark.read.format("sequence").option("kind", kind).option("n", "1000").option("parts", "7").load()
        got = rows.orderBy("pos").collect()
        assert [r.pos for r in got] == list(range(1000))
        assert [r.key for r in got] == generator.keys(kind, np.arange(1000)).tolist()
    from evensort.functions.keys import mix32

    mixed = spark.range(1000).select(mix32(F.col("id")).alias("m")).collect()
    assert [r.m for r in mixed] == generator.mix32(np.arange(1000)).tolist()


def test_amplified_sequence(spark):
    seq = spark.createDataFrame([(i, i) for i in range(10)], "pos bigint, key bigint")
    out = workloads.amplify(seq, 3).collect()
    assert sorted(r.pos for r in out) == list(range(30)) and len({r.key for r in out}) == 30


def test_sorted_files_merge_as_a_stream(spark, tmp_path):
    rows = [(i, (i * 37) % 50) for i in range(300)]
    paths = []
    for part in range(3):
        own = sorted((r for r in rows if r[0] % 3 == part), key=lambda r: (r[1], r[0]))
        path = f"{tmp_path}/{part}.parquet"
        import pyarrow as pa

        pq.write_table(pa.table({"pos": [r[0] for r in own], "key": [r[1] for r in own]}), path)
        paths.append(path)
    got = [k for b in merge_files.merge_sorted_files(paths, "key", 32) for k in b.column("key").to_pylist()]
    assert got == sorted(r[1] for r in rows)
    assert list(merge_files.merge_sorted_files([], "key")) == []


def test_asof_and_range_joins_equal_pairs(spark):
    left = spark.createDataFrame([(i, i % 3, i * 7 % 20) for i in range(40)], "id int, g int, t int")
    right = spark.createDataFrame([(100 + i, i % 3, i * 11 % 20) for i in range(15)], "rid int, g int, t int")
    got = {r.id: r.rt for r in joins.asof(left, right, "g", "t", {"rt": "t"}).collect()}
    rights = right.collect()
    for r in left.collect():
        assert got[r.id] == max((x.t for x in rights if x.g == r.g and x.t <= r.t), default=None)
    spans = spark.createDataFrame([(0, 5), (3, 17), (9, 9)], "lo int, hi int")
    pairs = joins.range_join(left, spans, "t", "lo", "hi", [4, 8, 12]).count()
    assert pairs == sum(lo < r.t <= hi for r in left.collect() for lo, hi in ((0, 5), (3, 17), (9, 9)))
    together = joins.co_partition(left.select("g", "id"), right.select("g", "rid"), "g", [0, 1], 3)
    assert together.count() == sum(r.g == x.g for r in left.collect() for x in rights)


def test_exact_cuts_join_splits_a_hot_key(spark):
    left = spark.createDataFrame([(i, 1 if i % 10 else i) for i in range(100)], "pos bigint, key bigint")
    right = spark.createDataFrame([(1, "a"), (1, "b"), (50, "c")], "key bigint, v string")
    out = joins.exact_cuts_join(left, right, 4)
    assert out.count() == left.join(right, "key").count()
    assert out.where("key = 1").select("part").distinct().count() >= 3


def test_pairs_of_a_hot_key_are_counted_not_formed(spark):
    left = spark.createDataFrame([("h", i * 37 % 101) for i in range(200)] + [("a", 5), ("a", 5), ("z", 9), ("l", 1), (None, 1), ("a", None)], "key string, value bigint")
    right = spark.createDataFrame([("h", i * 11 % 90) for i in range(150)] + [("a", 5), ("a", 6), ("a", 7), ("z", 9), ("r", 1), (None, 2), ("h", None)], "key string, value bigint")
    rows = [r for r in right.collect() if r.value is not None]
    want = {}
    for x in left.collect():
        n = sum(x.key == y.key and x.value < y.value for y in rows) if x.key is not None and x.value is not None else 0
        if n:
            want[x.key] = want.get(x.key, 0) + n
    for n_parts in (1, 5):
        assert {r.key: r.n_pairs for r in joins.exact_cuts_counts(left, right, n_parts).collect()} == want
    none = joins.exact_cuts_counts(left.where("false"), right, 3)
    assert none.collect() == [] and none.schema["n_pairs"].dataType.simpleString() == "bigint"
    # 10 ** 11 pairs: forming them would take minutes
    many = spark.range(1_000_000).select((F.col("id") % 2).alias("key"), F.expr("id div 2").alias("value"))
    assert [r.n_pairs for r in joins.exact_cuts_counts(many, many, 4).collect()] == [500_000 * 499_999 // 2] * 2


def test_dearest_of_equal_prices_is_the_first(spark, tmp_path):
    rows = [(1, 7, 5.0), (2, 7, 9.0), (3, 7, 9.0), (4, 7, 9.0), (5, 8, 1.0), (6, 8, None), (7, 9, None), (None, 10, 4.0), (8, 10, 3.0)]
    spark.createDataFrame(rows, "o_orderkey bigint, o_custkey bigint, o_totalprice double").coalesce(1).write.parquet(f"{tmp_path}/orders.parquet")
    got = {r.o_custkey: (r.dearest, r.price) for r in catalog.queries()["agg_max_by"](spark, str(tmp_path)).collect()}
    assert got == {7: (2, 9.0), 8: (5, 1.0), 9: (None, None), 10: (8, 4.0)}


def timed_runs(spark, path):
    rows = [("A", 1, 8.0), ("A", 1, 16.0), ("A", 4, 4.0), ("N", 1, 10.0), ("N", 4, 6.0), ("N", 4, 2.0), ("R", 4, 1.0)]
    spark.createDataFrame(rows, "l_returnflag string, l_linenumber int, l_quantity double").write.parquet(f"{path}/lineitem.parquet")


def test_efficiency_is_of_the_table(spark, tmp_path):
    timed_runs(spark, tmp_path)
    got = catalog.queries()["efficiency_fixed"](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == [("A", 1, 1.0), ("A", 4, 0.75), ("N", 1, 1.0), ("N", 4, 0.625)]


def example_orders(spark, path, n):
    rows = [(i, "5-LOW" if i % 6 == 2 else "1-URGENT") for i in range(n)]
    spark.createDataFrame(rows, "o_orderkey bigint, o_orderpriority string").write.parquet(f"{path}/orders.parquet")


def test_example_divides_duplicates_of_the_table(spark, tmp_path):
    """Six rows are those of the worked example; more of them keep its shares."""
    for n in (6, 61):
        example_orders(spark, f"{tmp_path}/{n}", n)
        got = sorted(map(tuple, catalog.queries()["example_duplicates"](spark, f"{tmp_path}/{n}").collect()))
        keys = [4 if i % 6 == 2 else 1 for i in range(n)]
        rank = {i: r for r, i in enumerate(sorted(range(n), key=lambda i: (keys[i], i)))}
        assert got == [(i, keys[i], i // -(-n // 2), rank[i] * 2 // n, int(keys[i] > 1), rank[i]) for i in range(n)]


def test_example_sorts_the_table(spark, tmp_path):
    example_orders(spark, tmp_path, 60)
    got = sorted(map(tuple, catalog.queries()["example_four_step"](spark, str(tmp_path)).collect()))
    keys = generator.mix32(np.arange(60)).tolist()
    rank = {i: r for r, i in enumerate(sorted(range(60), key=keys.__getitem__))}
    pivot = min(sorted(keys[:30])[15], sorted(keys[30:])[15])
    assert got == [(i, keys[i], i // 30, rank[i] * 2 // 60, int(keys[i] > pivot), rank[i]) for i in range(60)]


def test_speed_ratio_is_of_the_table(spark, tmp_path):
    timed_runs(spark, tmp_path)
    got = catalog.queries()["speed_ratio_fixed"](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == [("A", 1, 0.833333), ("A", 4, 1.0), ("N", 1, 1.0), ("N", 4, 1.0), ("R", 4, 4.0)]


def test_cogrouped_sides_of_one_parent(spark):
    rows = spark.createDataFrame([(i, i % 2, i * 7 % 5) for i in range(20)], "pos bigint, g int, key int")
    left, right = rows.where("pos < 9 OR g = 0").where("pos < 15"), rows.where("pos >= 5 AND g = 1")
    got = udfs.cogroup_merge(left.select("g", "key", "pos"), right.select("g", "key", "pos"), "g").collect()
    for g in (0, 1):
        want = sorted([(r.key, s, r.pos) for s, side in enumerate((left, right)) for r in side.where(f"g = {g}").collect()])
        assert [(r.key, r.side, r.pos) for r in sorted(got, key=lambda r: r.rnk) if r.g == g] == want


def test_global_windows_on_empty_parts(spark):
    seq = spark.createDataFrame([(i, i // 2) for i in range(5)], "pos bigint, key bigint")
    s = sorter.parallel_sort(seq, "exact", 3, 12)
    assert [r.before for r in windows.lag(s, "pos").orderBy("rnk").collect()] == [None, 0, 1, 2, 3]
    assert [r.dense_rank for r in windows.dense_rank(s).orderBy("rnk").collect()] == [1, 1, 2, 2, 3]
    assert [r.running for r in windows.running_sum(s, F.col("key")).orderBy("rnk").collect()] == [0, 0, 1, 2, 4]
    assert [r.tile for r in windows.ntile(s, 3).orderBy("rnk").collect()] == [1, 1, 2, 2, 3]


def test_presorted_and_shuffled_are_told_apart(spark):
    up = spark.createDataFrame([(i, i) for i in range(50)], "pos bigint, key bigint")
    down = up.withColumn("key", -F.col("key"))
    assert tuple(measures.presortedness(up, 50).first()) == (50, 0, 0)
    assert tuple(measures.presortedness(down, 50).first()) == (50, 49, 49)


def test_bucketed_sink_and_measures(spark):
    rows = spark.createDataFrame([(i, i % 5) for i in range(100)], "pos bigint, key bigint")
    spark.sql("DROP TABLE IF EXISTS bucketed_rows")
    assert io.save_bucketed(rows, "bucketed_rows", "key").count() == 100
    spark.sql("DROP TABLE bucketed_rows")
    timed = measures.elapsed(lambda: rows, runs=2)
    assert timed["runs"] == 2 and timed["mean"] > 0
    assert set(measures.stage_times(rows, 2, 2)) == {"block_sort", "select", "route", "merge"}
    assert measures.memory(spark, lambda: rows.repartition(3, "key"))["shuffle_write"] > 0


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the tables")
def test_claims_in_shape(spark):
    bounds = bench.claims(spark, SF, (2, 12, 24))
    assert min(bounds["exact"].values()) > 0.98
    assert bounds["regular"][24] < 0.2 < bounds["stable_snap"][24] < bounds["exact"][24]
    work = bench.kernel_work(5000)
    assert work["three_way/dup3"]["comparisons"] < work["merge_block/dup3"]["comparisons"] * 2
    assert work["branchless/uniform_int"]["branches"] < work["intro/uniform_int"]["branches"]
    even = bench.native_vs_exact(spark, SF, 8)
    assert even["exact"] < 1.01 and even["native"] > 2


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the tables")
def test_stream_restarts_from_its_checkpoint(spark):
    counted = streams.tumbling(streams.events(spark, SF), "1 day", "event_type")
    assert streams.drain(counted, "complete").agg(F.sum("n")).first()[0] == io.load(spark, SF, "events").count()
    assert streams.drain(counted, "update").agg(F.sum("n")).first()[0] == io.load(spark, SF, "events").count()


@pytest.mark.skipif(not os.path.isdir(SF), reason="needs the tables")
def test_experiment_drivers_run(spark):
    timed = bench.fig_time(spark, SF, 4, ("exact", "regular"), ("dup3",), runs=1)
    assert set(timed) == {"exact/dup3", "regular/dup3"} and min(timed.values()) > 0
    assert set(bench.fig_block_sorters(spark, SF, 2, ("intro", "spark"), ("dup3",))) == {"intro/dup3", "spark/dup3"}
    assert set(bench.fig_mergers(spark, SF, 2, ("pairs", "resort"), ("dup3",))) == {"pairs/dup3", "resort/dup3"}


def test_dataframe_sugar(spark):
    import evensort
    from evensort.functions.keys import By

    rows = spark.createDataFrame([(i, i * 7 % 10, f"p{i}") for i in range(30)], "id bigint, key int, part string")
    got = rows.drop("part").transform(evensort.sort([By("key", desc=True)], pos="id", method="exact", n_blocks=3, n_parts=4)).collect()
    want = sorted(range(30), key=lambda i: (-(i * 7 % 10), i))
    assert [r.id for r in sorted(got, key=lambda r: r.rnk)] == want and {r.part for r in got} == {0, 1, 2, 3}
    first = rows.transform(evensort.top(["key", "id"], 5, n_blocks=3, n_parts=4)).collect()
    assert sorted((r.key, r.id) for r in first) == sorted((i * 7 % 10, i) for i in range(30))[:5] and first[0].part.startswith("p")
    assert [r.value for r in rows.transform(evensort.quantiles("id", [0.5, 1.0])).collect()] == [14, 29]


def test_sketches_stay_within_their_bounds(spark):
    rows = spark.range(20_000).select((F.col("id") * 7919 % 20_000).alias("v"), (F.col("id") % 3000).alias("g"))
    exact = 3000
    assert abs(rows.agg(F.approx_count_distinct("g", 0.02)).first()[0] - exact) <= 4 * 0.02 * exact
    got = rows.agg(F.approx_percentile("v", F.array(F.lit(0.1), F.lit(0.5), F.lit(0.9)), 1000)).first()[0]
    assert all(abs(v - q * 20_000) <= 20_000 / 1000 + 1 for v, q in zip(got, (0.1, 0.5, 0.9)))
    kll = rows.selectExpr("kll_sketch_agg_bigint(v) AS s").selectExpr("kll_sketch_get_quantile_bigint(s, 0.5D) AS q").first().q
    assert abs(kll - 10_000) <= 0.03 * 20_000


def test_sample_is_seeded_and_near_its_rate(spark):
    rows = spark.range(20_000)
    a, b = (sorted(r.id for r in rows.sample(0.1, 5).collect()) for _ in range(2))
    assert a == b and abs(len(a) - 2000) < 6 * (20_000 * 0.09) ** 0.5
    by = rows.withColumn("g", F.col("id") % 2).sampleBy("g", {0: 0.2, 1: 0.0}, 3)
    assert by.where("g = 1").count() == 0 and by.count() > 1500


def test_text_round_trip(spark):
    rows = spark.createDataFrame([(f"line {i} é",) for i in range(50)], "value string")
    assert sorted(r.value for r in io.roundtrip(rows, "text").collect()) == sorted(f"line {i} é" for i in range(50))


def test_a_stream_goes_on_where_it_stopped(spark, tmp_path):
    """Two runs of one query on one checkpoint: the second reads only what is new."""
    source, state, sink = (f"{tmp_path}/{n}" for n in ("in", "state", "out"))
    schema = "id bigint, g string"

    def run():
        stream = spark.readStream.schema(schema).parquet(source)
        stream.writeStream.format("parquet").option("checkpointLocation", state).option("path", sink).trigger(availableNow=True).start().awaitTermination()
        return spark.read.parquet(sink).count()

    spark.createDataFrame([(i, "a") for i in range(10)], schema).write.parquet(source)
    assert run() == 10
    spark.createDataFrame([(i, "b") for i in range(10, 17)], schema).write.mode("append").parquet(source)
    assert run() == 17 and run() == 17


def test_asof_spreads_a_hot_key(spark):
    left = spark.createDataFrame([(i, 1 if i % 8 else i % 5, i * 37 % 400) for i in range(400)] + [(900, None, 3), (901, 1, None)], "id int, by int, t int")
    right = spark.createDataFrame([(100 + i, 1 if i % 9 else 2, i * 53 % 390) for i in range(60)] + [(7, None, 1)], "rid int, by int, t int")
    out = joins.asof(left, right, "by", "t", {"rt": "t"}, n_parts=6)
    got = {r.id: r.rt for r in out.collect()}
    assert len(got) == 402 and out.columns == ["id", "by", "t", "rt"]
    rights = right.collect()
    for r in left.collect():
        want = max((x.t for x in rights if r.by is not None and x.by == r.by and r.t is not None and x.t <= r.t), default=None)
        assert got[r.id] == want, r


def test_what_a_re_sort_meets_in_almost_sorted_runs():
    work = bench.merger_work()
    for s in ("uniform_int", "almost_sorted", "dup3"):
        assert work[f"tournament/{s}"]["comparisons"] < work[f"resort/{s}"]["comparisons"] / 3
    assert work["tournament/uniform_int"]["comparisons"] < work["binary_heap/uniform_int"]["comparisons"]
    # introsort ends in heapsort there, and not on random runs
    assert work["resort/almost_sorted"]["fallbacks"] > 0 == work["resort/uniform_int"]["fallbacks"]
    assert work["resort/almost_sorted"]["comparisons"] > 1.5 * work["resort/uniform_int"]["comparisons"]


def test_counted_work_of_block_sorters():
    work = bench.kernel_work()
    assert all(w["fallbacks"] == 0 for w in work.values())
    for s in ("uniform_int", "almost_sorted"):
        assert work[f"branchless/{s}"]["branches"] < work[f"intro/{s}"]["branches"] / 4
    assert work["three_way/dup3"]["comparisons"] == min(work[f"{k}/dup3"]["comparisons"] for k in ("plain_quick", "intro", "branchless", "three_way", "merge_block"))
