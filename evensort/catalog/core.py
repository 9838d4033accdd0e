"""Queries of the sort itself: skeleton, pivot rules, cuts, kernels, mergers, measures."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.keys import MIX, By
from ..operators import blocks, kernels, partition, pivots, rank, sorter
from ..plans import measures
from ..sources import io, workloads

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
N_BLOCKS, N_PARTS = 8, 8
THREADS = (1, 2, 4, 12, 24, 48)
RATE = 0.05


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


# ---- SQL of the sequences ----


def mix32_sql(x: str) -> str:
    a, c, b, d = MIX
    h = f"((({x}) * {a} + {c}) % 4294967296)"
    for shift, m in ((16, b), (15, d)):
        h = f"((xor({h}, {h} >> {shift}) * {m}) % 4294967296)"
    return f"xor({h}, {h} >> 16)"


def mix62_sql(x: str, n: str) -> str:
    return f"({mix32_sql(x)} * 1073741824 + {mix32_sql(f'{x} + {n}')} % 1073741824)"


SEQ = {
    "uniform_int": f"SELECT o_orderkey AS pos, {mix32_sql('o_orderkey')} AS key FROM orders",
    "uniform_float": "SELECT o_orderkey AS pos, CAST(o_totalprice / 500000 AS FLOAT) AS key FROM orders",
    "almost_sorted": """SELECT event_id AS pos, coalesce(t, event_id) AS key FROM events LEFT JOIN (
        SELECT a AS f, b AS t FROM w UNION ALL SELECT b, a FROM w) ON event_id = f""",
    "dup3": "SELECT o_orderkey AS pos, CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END AS key FROM orders",
    "pair": f"SELECT o_orderkey AS pos, {mix62_sql('o_orderkey', '(SELECT count(*) FROM orders)')} AS key, o_orderkey AS idx FROM orders",
    "particle": f"SELECT vec_id AS pos, {mix62_sql('vec_id', '(SELECT count(*) FROM embeddings)')} AS key, embedding AS e FROM embeddings",
    "strings": "SELECT doc_id AS pos, text AS key FROM documents",
    "dates": "SELECT o_orderkey AS pos, o_orderdate AS key FROM orders",
    "region": "SELECT CAST(r_regionkey AS BIGINT) AS pos, r_name AS key FROM region",
    "all_equal": "SELECT o_orderkey AS pos, 7 AS key FROM orders",
    "price": "SELECT o_orderkey AS pos, o_totalprice AS key FROM orders",
    "one_four": "SELECT o_orderkey AS pos, CASE o_orderpriority WHEN '5-LOW' THEN 4 ELSE 1 END AS key FROM orders",
}
_SWAPS = """w AS (SELECT ((i * 2) * 7919 + 17) % n AS a, ((i * 2 + 1) * 7919 + 17) % n AS b FROM (
    SELECT n, unnest(range(h)) AS i FROM (SELECT count(*) AS n, CAST(floor(sqrt(count(*))) AS BIGINT) // 2 AS h FROM events)))"""


def with_seq(name: str) -> str:
    """CTEs: s (the sequence), n (its size), r (with rnk), b (with block and place idx, m rows)."""
    return f"""WITH {_SWAPS}, s AS ({SEQ[name]}), n AS (SELECT count(*) AS n FROM s),
        r AS (SELECT *, row_number() OVER (ORDER BY key NULLS FIRST, pos) - 1 AS rnk FROM s)"""


def with_blocks(name: str, n_blocks: int, n_parts: int, samples: int | None = None) -> str:
    s = n_parts - 1 if samples is None else samples
    return (
        with_seq(name)
        + f""", b AS (SELECT s.*, pos // ((n + {n_blocks} - 1) // {n_blocks}) AS block FROM s, n),
        i AS (SELECT *, row_number() OVER (PARTITION BY block ORDER BY key, pos) - 1 AS spot, count(*) OVER (PARTITION BY block) AS m FROM b),
        q AS (SELECT i.key, row_number() OVER (ORDER BY i.key) AS place, count(*) OVER () AS s_n
              FROM i, (SELECT unnest(range(1, {s} + 1)) AS j) WHERE spot = (j * m) // ({s} + 1)),
        p AS (SELECT k, q.key AS pivot_key FROM q, (SELECT unnest(range(1, {n_parts})) AS k) WHERE place = (k * s_n + {n_parts} - 1) // {n_parts})"""
    )


def random_pivots_sql(name: str, n_parts: int, rate: float = RATE) -> str:
    return (
        with_seq(name)
        + f""", q AS (SELECT key, row_number() OVER (ORDER BY key) AS place, count(*) OVER () AS s_n FROM s
              WHERE {mix32_sql("pos")} < {int(rate * (1 << 32))}),
        p AS (SELECT k, q.key AS pivot_key FROM q, (SELECT unnest(range(1, {n_parts})) AS k) WHERE place = (k * s_n + {n_parts} - 1) // {n_parts})"""
    )


def cuts_sql(name: str, n_parts: int) -> str:
    """CTE c: the exact cuts."""
    return (
        with_seq(name)
        + f""", g AS (SELECT key, min(rnk) AS less, max(rnk) + 1 AS less_eq FROM r GROUP BY key),
        t AS (SELECT k, (k * n + {n_parts} - 1) // {n_parts} AS cut_rank FROM n, (SELECT unnest(range(1, {n_parts})) AS k)),
        c AS (SELECT k, key AS pivot_key, cut_rank - less AS take, cut_rank, less, less_eq FROM t JOIN g ON less < cut_rank AND cut_rank <= less_eq)"""
    )


def snap_sql(name: str, n_blocks: int, n_parts: int) -> str:
    """CTE x: rows with their partition under cuts snapped to block runs."""
    return (
        cuts_sql(name, n_parts)
        + f""", b AS (SELECT r.*, pos // ((n + {n_blocks} - 1) // {n_blocks}) AS block, row_number() OVER (PARTITION BY key ORDER BY pos) - 1 AS tau FROM r, n),
        e AS (SELECT key, block, sum(count(*)) OVER (PARTITION BY key ORDER BY block) AS run FROM b GROUP BY key, block),
        z AS (SELECT k, pivot_key, coalesce(max(CASE WHEN run <= take THEN run END), 0) AS take FROM c JOIN e ON e.key = c.pivot_key GROUP BY k, pivot_key),
        x AS (SELECT b.pos, b.key, b.rnk, (SELECT count(*) FROM z WHERE z.pivot_key < b.key OR (z.pivot_key = b.key AND z.take <= b.tau)) AS part FROM b)"""
    )


def routed_sql(method: str, name: str, n_blocks: int, n_parts: int) -> str:
    """CTEs ending in x (pos, key, rnk, part)."""
    if method == "exact":
        return with_seq(name) + f", x AS (SELECT pos, key, rnk, (rnk * {n_parts}) // n AS part FROM r, n)"
    if method == "stable_snap":
        return snap_sql(name, n_blocks, n_parts)
    head = with_blocks(name, n_blocks, n_parts) if method == "regular" else random_pivots_sql(name, n_parts)
    return head + ", x AS (SELECT r.pos, r.key, r.rnk, (SELECT count(*) FROM p WHERE p.pivot_key < r.key) AS part FROM r)"


def sizes_sql(n_parts: int) -> str:
    return f"""(SELECT part, coalesce(n, 0) AS n FROM (SELECT unnest(range({n_parts})) AS part)
        LEFT JOIN (SELECT part, count(*) AS n FROM x GROUP BY part) USING (part))"""


# ---- sequences on Spark ----


def seq(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    if name in workloads.SEQUENCES:
        return workloads.sequence(name, spark, sf_dir)
    orders = lambda c: io.load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("pos"), c.alias("key"))
    if name == "strings":
        return io.load(spark, sf_dir, "documents").select(F.col("doc_id").alias("pos"), F.col("text").alias("key"))
    if name == "region":
        return io.load(spark, sf_dir, "region").select(F.col("r_regionkey").cast("bigint").alias("pos"), F.col("r_name").alias("key"))
    one_four = F.when(F.col("o_orderpriority") == "5-LOW", 4).otherwise(1)
    return orders({"dates": F.col("o_orderdate"), "all_equal": F.lit(7), "price": F.col("o_totalprice"), "one_four": one_four}[name])


def narrow(name, spark, sf_dir):
    return seq(name, spark, sf_dir).select("pos", "key")


def blocked(name, spark, sf_dir, n_blocks=N_BLOCKS):
    return blocks.assign_blocks(narrow(name, spark, sf_dir), n_blocks)


COLS = ("pos", "key", "part", "rnk")


def _add_sequences() -> None:
    for name in workloads.SEQUENCES:
        if name == "particle":
            flat = ["mass", *[f"{g}[{i}] AS {g[0]}{i}" for g in ("position", "velocity", "acceleration") for i in range(3)], "potential"]
            picks = ["mass", *[f"{g}{i}" for g in "pva" for i in range(3)], "potential"]
            sql = ", ".join(f"CAST(e[{i + 1}] AS DOUBLE) AS {c}" for i, c in enumerate(picks))
            query("seq_particle", f"{with_seq(name)} SELECT pos, key, {sql} FROM s")(
                lambda spark, d, flat=flat: seq("particle", spark, d).selectExpr("pos", "key", *flat)
            )
        else:
            query(f"seq_{name}", f"{with_seq(name)} SELECT * FROM s")(lambda spark, d, name=name: seq(name, spark, d))


def _add_sorts() -> None:
    exact_on = [*workloads.SEQUENCES, "strings", "dates", "all_equal"]
    jobs = [("exact", s, f"sort_exact_{s}") for s in exact_on]
    jobs += [("regular", s, f"sort_regular_{s}") for s in workloads.SEQUENCES]
    jobs += [(m, s, f"sort_{m}_{s}") for m in ("random_sample", "stable_snap") for s in ("dup3", "uniform_int")]
    for method, s, name in jobs:
        query(name, routed_sql(method, s, N_BLOCKS, N_PARTS) + " SELECT pos, key, part, rnk FROM x")(
            lambda spark, d, m=method, s=s: sorter.parallel_sort(narrow(s, spark, d), m, N_BLOCKS, N_PARTS, rate=RATE).df.select(*COLS)
        )
    query("sort_exact_tiny_region", routed_sql("exact", "region", N_BLOCKS, N_PARTS) + " SELECT pos, key, part, rnk FROM x")(
        lambda spark, d: sorter.parallel_sort(narrow("region", spark, d), "exact", N_BLOCKS, N_PARTS).df.select(*COLS)
    )
    for s in ("dup3", "uniform_int", "strings"):
        query(f"sort_native_{s}", with_seq(s) + " SELECT pos, key, rnk FROM r")(
            lambda spark, d, s=s: sorter.parallel_sort(narrow(s, spark, d), "native", n_parts=N_PARTS).df.select("pos", "key", "rnk")
        )
    query("sort_single", routed_sql("exact", "uniform_int", 1, 1) + " SELECT pos, key, part, rnk FROM x")(
        lambda spark, d: sorter.parallel_sort(narrow("uniform_int", spark, d), "exact", 1, 1).df.select(*COLS)
    )
    query("sort_exact_two_level", routed_sql("exact", "dup3", N_BLOCKS, 12) + " SELECT pos, key, part, rnk FROM x")(
        lambda spark, d: sorter.two_level(narrow("dup3", spark, d), 12).df.select(*COLS)
    )
    query("sort_exact_unstable_dup3", f"{routed_sql('exact', 'dup3', 8, N_PARTS)} SELECT part, key, count(*) AS n FROM x GROUP BY part, key")(_unstable)
    query("sort_regular_tiebroken_dup3", _tiebroken_sql())(_tiebroken)
    # repeated halving: 2^3 parts, each split at ceil(n / 2)
    query("sort_parallel_quick", with_seq("dup3") + " SELECT pos, key, rnk FROM r")(
        lambda spark, d: sorter.parallel_quick(narrow("dup3", spark, d)).df.select("pos", "key", "rnk")
    )
    query("argsort_pair", with_seq("pair") + " SELECT rnk, pos FROM r")(lambda spark, d: sorter.argsort(seq("pair", spark, d)))


def _unstable(spark, d):
    own = narrow("dup3", spark, d)
    routed = partition.route_by_exact_cuts(own, pivots.exact(own, N_PARTS), stable=False)
    return routed.groupBy("part", "key").agg(F.count("*").alias("n"))


def _tiebroken(spark, d):
    """Regular sampling on (key, pos): duplicates become distinct."""
    own = narrow("dup3", spark, d).withColumn("key", F.struct("key", "pos"))
    out = sorter.parallel_sort(own, "regular", N_BLOCKS, N_PARTS).df
    return out.select("pos", F.col("key.key").alias("key"), "part", "rnk")


def _tiebroken_sql():
    head = with_blocks("dup3", N_BLOCKS, N_PARTS)
    head = head.replace("SELECT i.key, row_number() OVER (ORDER BY i.key) AS place", "SELECT i.key, i.pos, row_number() OVER (ORDER BY i.key, i.pos) AS place")
    head = head.replace("SELECT k, q.key AS pivot_key FROM q", "SELECT k, q.key AS pivot_key, q.pos AS pivot_pos FROM q")
    return head + " SELECT r.pos, r.key, (SELECT count(*) FROM p WHERE pivot_key < r.key OR (pivot_key = r.key AND pivot_pos < r.pos)) AS part, r.rnk FROM r"


def _add_steps() -> None:
    lay = "SELECT pos // ((n + 7) // 8) AS block, pos, key FROM s, n"
    query("blocks_layout", f"{with_seq('uniform_int')} SELECT block, count(*) AS n, min(pos) AS min_pos, max(pos) AS max_pos FROM ({lay}) GROUP BY block")(
        lambda spark, d: blocks.layout(blocked("uniform_int", spark, d))
    )
    ranked = "SELECT pos, key, block, row_number() OVER (PARTITION BY block ORDER BY key, pos) - 1 AS idx"
    query("blocks_sorted", f"{with_seq('uniform_int')} {ranked} FROM ({lay})")(lambda spark, d: blocks.sort_blocks(blocked("uniform_int", spark, d)))
    for kernel in [*kernels.SORTERS, "spark"]:
        query(f"kernel_{kernel}", f"{with_seq('pair')} {ranked} FROM ({lay})")(
            lambda spark, d, k=kernel: blocks.sort_blocks(blocked("pair", spark, d), k)
        )
    for kernel in ("three_way", "branchless", "intro"):
        query(f"kernel_{kernel}_dup3", f"{with_seq('dup3')} {ranked} FROM ({lay})")(
            lambda spark, d, k=kernel: blocks.sort_blocks(blocked("dup3", spark, d), k)
        )
    query("kernel_three_way_ops")(_three_way_ops)
    for method in ("regular", "exact"):
        query(
            f"piece_sizes_{method}",
            routed_sql(method, "dup3", N_BLOCKS, N_PARTS) + ", f AS (SELECT pos // ((n + 7) // 8) AS block, part FROM x, n) SELECT block, part, count(*) AS n FROM f GROUP BY block, part",
        )(lambda spark, d, m=method: partition.piece_sizes(_routed(m, "dup3", spark, d)))
    offs = "SELECT part, n, coalesce(CAST(sum(n) OVER (ORDER BY part ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT), 0) AS part_offset FROM "
    query("partition_offsets", routed_sql("regular", "dup3", N_BLOCKS, N_PARTS) + offs.join(["", sizes_sql(N_PARTS)]))(
        lambda spark, d: partition.offsets(_routed("regular", "dup3", spark, d), N_PARTS)
    )
    # the worked examples' jobs on a table: two blocks, two parts, both rules
    for name, s in (("example_four_step", "uniform_int"), ("example_duplicates", "one_four")):
        sql = " SELECT r.pos, r.key, pos // ((n + 1) // 2) AS block, (rnk * 2) // n AS exact_part, (SELECT count(*) FROM p WHERE p.pivot_key < r.key) AS regular_part, rnk FROM r, n"
        query(name, with_blocks(s, 2, 2) + sql)(lambda spark, d, s=s: _example(narrow(s, spark, d)))


def _three_way_ops(spark, d):
    """Counted work of two sorters on each block of the three-valued key: three-way splitting
    stays within a multiple of rows times distinct keys."""
    schema = "block bigint, kernel string, n bigint, distinct_keys bigint, comparisons bigint, moves bigint, depth bigint, bad_partitions bigint, fallbacks bigint"

    def run(part: pd.DataFrame) -> pd.DataFrame:
        keys, rows = part.sort_values("pos")["key"].to_numpy(np.int64), []
        for k in ("three_way", "intro"):
            s = kernels.Stats()
            kernels.permutation(k, keys, s)
            rows.append((part["block"].iloc[0], k, len(keys), len(np.unique(keys)), s.comparisons, s.moves, s.depth, s.bad_partitions, s.fallbacks))
        return pd.DataFrame(rows, columns=[c.split()[0] for c in schema.split(", ")])

    return blocked("dup3", spark, d).groupBy("block").applyInPandas(run, schema)


def _example(own):
    """Rows sorted by exact cuts, with their block and the part that regular pivots give them."""
    n = own.count()
    exact = sorter.parallel_sort(own, "exact", 2, 2, n=n).df.withColumnRenamed("part", "exact_part")
    both = partition.route_by_pivots(exact, pivots.regular(blocks.assign_blocks(own, 2, n), 2))
    return both.select("pos", "key", F.expr(f"pos div {blocks.block_length(n, 2)}").alias("block"), "exact_part", F.col("part").alias("regular_part"), "rnk")


def _routed(method, name, spark, d, n_blocks=N_BLOCKS, n_parts=N_PARTS):
    own = blocked(name, spark, d, n_blocks)
    if method == "regular":
        return partition.route_by_pivots(own, pivots.regular(own, n_parts))
    if method == "random_sample":
        return partition.route_by_pivots(own, pivots.random_sample(own, n_parts, RATE))
    cuts = pivots.exact(own, n_parts)
    return partition.route_by_exact_cuts(own, pivots.stable_snap(own, cuts) if method == "stable_snap" else cuts)


def _add_pivots() -> None:
    query("pivots_regular", with_blocks("uniform_int", N_BLOCKS, N_PARTS) + " SELECT k, pivot_key FROM p")(
        lambda spark, d: pivots.pivots_frame(spark, pivots.regular(blocked("uniform_int", spark, d), N_PARTS), T.LongType())
    )
    query("pivots_regular_capped", with_blocks("uniform_int", N_BLOCKS, N_PARTS, 3) + " SELECT k, pivot_key FROM p")(
        lambda spark, d: pivots.pivots_frame(spark, pivots.regular(blocked("uniform_int", spark, d), N_PARTS, per_block=3), T.LongType())
    )
    query("pivots_random_sample", random_pivots_sql("uniform_int", N_PARTS) + " SELECT k, pivot_key FROM p")(
        lambda spark, d: pivots.pivots_frame(spark, pivots.random_sample(narrow("uniform_int", spark, d), N_PARTS, RATE), T.LongType())
    )
    cut_cols = " SELECT k, pivot_key, take, cut_rank, less, less_eq FROM c"

    def cuts(s, strategy="auto", n_parts=N_PARTS):
        def run(spark, d):
            own = blocked(s, spark, d)
            return pivots.cuts_frame(spark, pivots.exact(own, n_parts, strategy), own.schema["key"].dataType)

        return run

    for s in ("dup3", "uniform_int", "almost_sorted", "pair", "strings", "dates"):
        query(f"cuts_exact_{s}", cuts_sql(s, N_PARTS) + cut_cols)(cuts(s))
    for name, strategy in (("rank_search", "rank_search"), ("domain_bisect", "domain_bisect"), ("histogram", "histogram"), ("sketch_refine", "sketch_refine"), ("multiway", "multiway_search")):
        query(f"cuts_exact_{name}", cuts_sql("uniform_int", 5) + cut_cols)(cuts("uniform_int", strategy, 5))
    query("tie_quotas_dup3", cuts_sql("dup3", N_PARTS) + """, b AS (SELECT key, pos // ((n + 7) // 8) AS block FROM s, n),
        e AS (SELECT key, block, count(*) AS c_n, sum(count(*)) OVER (PARTITION BY key ORDER BY block) - count(*) AS base FROM b GROUP BY key, block)
        SELECT k, block, CAST(greatest(0, least(c_n, take - base)) AS BIGINT) AS quota FROM c JOIN e ON e.key = pivot_key""")(_quotas)  # fmt: skip
    query("cuts_inequality_check", cuts_sql("dup3", N_PARTS) + f" SELECT k, less, less_eq, less * {N_PARTS} <= k * n AND k * n <= less_eq * {N_PARTS} AS holds FROM c, n")(
        lambda spark, d: pivots.check_cuts(narrow("dup3", spark, d), pivots.exact(narrow("dup3", spark, d), N_PARTS), N_PARTS)
    )
    query("cuts_weighted_documents", """WITH g AS (SELECT lang AS key, CAST(sum(n_chars) AS BIGINT) AS n FROM documents GROUP BY lang),
        u AS (SELECT key, n, CAST(sum(n) OVER (ORDER BY key) - n AS BIGINT) AS less, CAST(sum(n) OVER () AS BIGINT) AS total FROM g)
        SELECT k, key AS pivot_key, (k * total + 7) // 8 AS cut_weight, less AS less_weight, n AS key_weight FROM u, (SELECT unnest(range(1, 8)) AS k)
        WHERE less < (k * total + 7) // 8 AND (k * total + 7) // 8 <= less + n""")(  # fmt: skip
        lambda spark, d: pivots.exact_weighted(io.load(spark, d, "documents", ["lang", "n_chars"]).withColumnRenamed("lang", "key"), "n_chars", 8)
    )
    query("exact_median_orders", with_seq("price") + " SELECT key AS median FROM r, n WHERE rnk = (n + 1) // 2 - 1")(
        lambda spark, d: spark.createDataFrame([(rank.exact_quantiles(narrow("price", spark, d), [0.5])[0],)], "median double")
    )
    shares = (0.01, 0.25, 0.5, 0.75, 0.99)
    pick = " UNION ALL ".join(f"SELECT CAST({s} AS DOUBLE) AS share, quantile_disc(l_extendedprice, {s}) AS value FROM lineitem" for s in shares)
    query("exact_quantiles_lineitem", pick)(_quantiles(shares))


def _quantiles(shares):
    def run(spark, d):
        own = io.load(spark, d, "lineitem", ["l_extendedprice"]).withColumnRenamed("l_extendedprice", "key")
        return spark.createDataFrame(list(zip(shares, rank.exact_quantiles(own, list(shares)))), "share double, value double")

    return run


def _quotas(spark, d):
    own = blocked("dup3", spark, d)
    return partition.tie_quotas(own, pivots.exact(own, N_PARTS))


def _add_mergers() -> None:
    for s in ("pair", "dup3"):
        for name, merger in (("tournament", "tournament"), ("heap", "binary_heap"), ("resort", "resort"), ("pairs", "pairs")):
            query(f"merge_{name}_{s}", routed_sql("exact", s, N_BLOCKS, N_PARTS) + " SELECT pos, key, part, rnk FROM x")(
                lambda spark, d, s=s, m=merger: sorter.parallel_sort(narrow(s, spark, d), "exact", N_BLOCKS, N_PARTS, merge=m).df.select(*COLS)
            )
    # the study's headline combination, and its regular-sampling counterpart
    for rule, s in [*(("exact", s) for s in workloads.SEQUENCES), ("regular", "dup3"), ("regular", "uniform_int")]:
        query(f"sort_{rule}_branchless_tournament_{s}", routed_sql(rule, s, N_BLOCKS, N_PARTS) + " SELECT pos, key, part, rnk FROM x")(
            lambda spark, d, r=rule, s=s: sorter.parallel_sort(narrow(s, spark, d), r, N_BLOCKS, N_PARTS, "branchless", "tournament").df.select(*COLS)
        )
    # block sorters under the tree, mergers over introsorted blocks
    for k in ("intro", "three_way"):
        query(f"sort_exact_{k}_tournament_dup3", routed_sql("exact", "dup3", N_BLOCKS, N_PARTS) + " SELECT pos, key, part, rnk FROM x")(
            lambda spark, d, k=k: sorter.parallel_sort(narrow("dup3", spark, d), "exact", N_BLOCKS, N_PARTS, k, "tournament").df.select(*COLS)
        )
    for m in ("binary_heap", "resort"):
        query(f"sort_exact_intro_{m}_almost_sorted", routed_sql("exact", "almost_sorted", N_BLOCKS, N_PARTS) + " SELECT pos, key, part, rnk FROM x")(
            lambda spark, d, m=m: sorter.parallel_sort(narrow("almost_sorted", spark, d), "exact", N_BLOCKS, N_PARTS, "intro", m).df.select(*COLS)
        )
    # the search in sorted blocks as the sort's own selection
    query("sort_exact_rank_search_dup3", routed_sql("exact", "dup3", N_BLOCKS, N_PARTS) + " SELECT pos, key, part, rnk FROM x")(
        lambda spark, d: sorter.parallel_sort(narrow("dup3", spark, d), "exact", N_BLOCKS, N_PARTS, "branchless", "tournament", "rank_search").df.select(*COLS)
    )
    query("cuts_exact_1000_parts", cuts_sql("uniform_int", 1000) + " SELECT k, pivot_key, take, cut_rank, less, less_eq FROM c")(
        lambda spark, d: pivots.cuts_frame(spark, pivots.exact(narrow("uniform_int", spark, d), 1000), T.LongType())
    )
    query("merge_auto_small_k", routed_sql("exact", "pair", 4, N_PARTS) + " SELECT pos, key, part, rnk FROM x")(
        lambda spark, d: sorter.parallel_sort(narrow("pair", spark, d), "exact", 4, N_PARTS, merge="auto").df.select(*COLS)
    )
    grid = [(r, b, m) for r in ("exact", "regular") for b in ("intro", "three_way", "branchless") for m in ("tournament", "binary_heap", "resort")]
    rows = ", ".join(f"('{r}', '{b}', '{m}', true)" for r, b, m in grid)
    query("merge_grid_agree", f"SELECT * FROM (VALUES {rows}) AS v(rule, block_sort, merger, agrees)")(lambda spark, d: _grid(spark, d, grid))
    cut = with_blocks("price", 1, 16) + ", h AS (SELECT key FROM r, n WHERE rnk IN (SELECT (k * n + 15) // 16 - 1 FROM n, (SELECT unnest(range(1, 16)) AS k)))"
    query("classify_splitter_tree", cut + " SELECT pos, (SELECT count(*) FROM h WHERE h.key < s.key) AS bucket FROM s")(_classify)


def _grid(spark, d, grid):
    own = narrow("particle", spark, d).persist()
    want = [r.pos for r in own.orderBy("key", "pos").collect()]
    out = []
    for r, b, m in grid:
        got = sorter.parallel_sort(own, r, 4, 4, b, m).df.select("pos", "rnk").collect()
        out.append((r, b, m, [x.pos for x in sorted(got, key=lambda x: x.rnk)] == want))
    return spark.createDataFrame(out, "rule string, block_sort string, merger string, agrees boolean")


def _classify(spark, d):
    own = narrow("price", spark, d)
    splitters = np.array([c.key for c in pivots.exact(own, 16)])

    @F.pandas_udf("bigint")
    def bucket(keys: pd.Series) -> pd.Series:
        return pd.Series(kernels.classify(keys.to_numpy(), splitters))

    return own.select("pos", bucket("key").alias("bucket"))


def _add_measures() -> None:
    for method in ("regular", "exact", "stable_snap", "random_sample"):
        for s in ("dup3", "uniform_int", "almost_sorted"):
            sql = f" SELECT CAST({N_PARTS} AS BIGINT) AS n_parts, CAST(sum(n) AS BIGINT) AS n_rows, max(n) AS max_n, min(n) AS min_n, round(max(n) * {N_PARTS} / sum(n), 6) AS imbalance FROM "
            query(f"balance_{method}_{s}", routed_sql(method, s, N_BLOCKS, N_PARTS) + sql + sizes_sql(N_PARTS))(
                lambda spark, d, m=method, s=s: measures.balance(_routed(m, s, spark, d), N_PARTS)
            )
    for method in ("regular", "exact", "stable_snap"):
        parts = []
        for t in THREADS:
            parts.append(f"SELECT * FROM ({routed_sql(method, 'dup3', t, t)} SELECT CAST({t} AS BIGINT) AS t, max(n) AS max_n, round(sum(n) / ({t} * max(n)), 6) AS bound FROM {sizes_sql(t)})")
        query(f"merge_bound_sweep_dup3{'' if method == 'exact' else '_' + method}", " UNION ALL ".join(parts))(lambda spark, d, m=method: _sweep(m, spark, d))
    ladder = (("documents", "lang"), ("events", "event_type"), ("lineitem", "l_discount"), ("lineitem", "l_quantity"), ("orders", "o_custkey"))
    lad = " UNION ALL ".join(f"SELECT '{c}' AS column_name, CAST(sum(n) AS BIGINT) AS n_rows, count(*) AS distinct_keys, max(n) AS top_count FROM (SELECT count(*) AS n FROM {t} GROUP BY {c})" for t, c in ladder)
    query("balance_skew_ladder", lad)(lambda spark, d: _ladder(spark, d, ladder))
    profile = "SELECT CAST(sum(n) AS BIGINT) AS n_rows, count(*) AS distinct_keys, max(n) AS top_count FROM (SELECT key, count(*) AS n FROM s GROUP BY key)"
    query("dup_lower_bound", f"{with_seq('dup3')} {profile}")(lambda spark, d: measures.pivot_only_lower_bound(narrow("dup3", spark, d)))
    query("key_profile", f"{with_seq('price')} {profile}")(lambda spark, d: measures.key_profile(narrow("price", spark, d)))
    runs = "v AS (SELECT l_returnflag AS method, CAST(l_linenumber AS BIGINT) AS t, avg(l_quantity) AS sec FROM lineitem GROUP BY l_returnflag, l_linenumber)"
    query("efficiency_fixed", f"WITH {runs} SELECT a.method, a.t, round(b.sec / (a.t * a.sec), 6) AS efficiency FROM v a JOIN v b ON a.method = b.method AND b.t = 1")(
        lambda spark, d: measures.efficiency(_mean_times(spark, d))
    )
    query("speed_ratio_fixed", f"WITH {runs} SELECT a.method, a.t, round(b.sec / a.sec, 6) AS ratio FROM v a JOIN v b ON a.t = b.t AND b.method = 'N'")(
        lambda spark, d: measures.speed_ratio(_mean_times(spark, d), "N")
    )
    grid = [(1, 1), (8, 8), (48, 48), (48, 12)]
    model = "(VALUES " + ", ".join(f"({b}, {p})" for b, p in grid) + ") AS v(b, p)"
    rounds = "CAST(ceil(ln(CAST(n AS DOUBLE)) / ln(CAST(4.0 AS DOUBLE) / 3.0)) AS BIGINT) + 1"
    query("selection_cost_model", f"WITH o AS (SELECT count(*) AS n FROM orders) SELECT n, CAST(b AS BIGINT) AS n_blocks, CAST(p AS BIGINT) AS n_parts, CAST(b * (p - 1) AS BIGINT) AS samples, {rounds} AS max_rounds, ({rounds}) * b * (p - 1) AS max_probes FROM o, {model}")(
        lambda spark, d: measures.selection_cost(spark, io.load(spark, d, "orders").count(), grid)
    )
    methods = ("exact", "regular", "random_sample", "stable_snap", "native")
    query("check_sorted_all_methods", " UNION ALL ".join(f"SELECT '{m}' AS method, count(*) AS n, CAST(0 AS BIGINT) AS inversions, CAST(0 AS BIGINT) AS overlaps FROM orders" for m in methods))(lambda spark, d: _checked(spark, d, methods))
    pre = []
    for s in ("almost_sorted", "uniform_int"):
        pre.append(f"SELECT * FROM ({with_seq(s)} SELECT '{s}' AS seq, count(*) AS n, (SELECT count(*) FROM s a JOIN s b ON b.pos = a.pos + 1 WHERE b.key < a.key) AS descents, max(abs(rnk - pos)) AS max_displacement FROM r)")
    query("presortedness_sequences", " UNION ALL ".join(pre))(_presorted)


def _mean_times(spark, d):
    """(method, t, sec) of the rows of lineitem as a log of runs: the flag is the method, the line
    number the threads, the quantity the seconds."""
    rows = io.load(spark, d, "lineitem", ["l_returnflag", "l_linenumber", "l_quantity"])
    return rows.groupBy(F.col("l_returnflag").alias("method"), F.col("l_linenumber").cast("bigint").alias("t")).agg(F.avg("l_quantity").alias("sec"))


def _sweep(method, spark, d):
    """Bounds at every number of threads.  Exact cuts of all of them come from one selection,
    and one pass over the rows counts the parts of all."""
    if method == "regular":
        out = None
        for t in THREADS:
            own = measures.merge_bound(_routed(method, "dup3", spark, d, t, t), t)
            out = own if out is None else out.unionByName(own)
        return out
    rows = narrow("dup3", spark, d)
    n = rows.count()
    ranks = sorted({r for t in THREADS for r in pivots.target_ranks(n, t)})
    by_rank = {c.rank: c for c in pivots.exact(rows, len(ranks) + 1, "histogram", n=n, ranks=ranks)}
    counts = rows.groupBy("key").agg(F.count("*").alias("n"))
    out = None
    for t in THREADS:
        cuts = [by_rank[r] for r in pivots.target_ranks(n, t)]
        if method == "stable_snap":
            own = measures.merge_bound(partition.route_by_exact_cuts(blocks.assign_blocks(rows, t, n), pivots.stable_snap(blocks.assign_blocks(rows, t, n), cuts)), t)
        else:
            # a part of exact cuts has the rows between two ranks: sizes need no routing
            ends = [0, *(c.rank for c in cuts), n]
            most = max(b - a for a, b in zip(ends, ends[1:]))
            own = counts.agg(F.sum("n").alias("n")).select(F.lit(t).cast("bigint").alias("t"), F.lit(most).cast("bigint").alias("max_n"), F.round(F.col("n") / (t * F.lit(most)), 6).alias("bound"))
        out = own if out is None else out.unionByName(own)
    return out


def _ladder(spark, d, ladder):
    out = None
    for t, c in ladder:
        own = measures.pivot_only_lower_bound(io.load(spark, d, t, [c]).withColumnRenamed(c, "key")).withColumn("column_name", F.lit(c))
        out = own if out is None else out.unionByName(own)
    return out


def _checked(spark, d, methods):
    out = None
    for m in methods:
        own = measures.check_sorted(sorter.parallel_sort(narrow("dup3", spark, d), m, N_BLOCKS, N_PARTS, rate=RATE).df).withColumn("method", F.lit(m))
        out = own if out is None else out.unionByName(own)
    return out


def _presorted(spark, d):
    out = None
    for s in ("almost_sorted", "uniform_int"):
        own = narrow(s, spark, d)
        made = measures.presortedness(own, own.count()).withColumn("seq", F.lit(s))
        out = made if out is None else out.unionByName(made)
    return out


for add in (_add_sequences, _add_sorts, _add_steps, _add_pivots, _add_mergers, _add_measures):
    add()

__all__ = ["ORACLES", "QUERIES", "By"]
