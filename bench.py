"""Headline queries on $BENCH_SF_DIR with local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)


def session(cpus: int):
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(max(8, cpus)))
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


#: The study's sorts and their parts, then consumers of sorted layouts.
HEADLINE = (
    "sort_exact_uniform_int", "sort_exact_uniform_float", "sort_exact_almost_sorted", "sort_exact_dup3", "sort_exact_pair", "sort_exact_particle",
    "sort_exact_branchless_tournament_uniform_int", "sort_exact_branchless_tournament_dup3",
    "sort_regular_uniform_int", "sort_regular_dup3", "sort_regular_pair", "sort_stable_snap_uniform_int", "sort_stable_snap_dup3",
    "sort_native_uniform_int", "sort_native_dup3", "sort_random_sample_uniform_int", "cuts_exact_histogram", "cuts_exact_sketch_refine",
    "cuts_exact_rank_search", "kernel_three_way_dup3", "kernel_branchless", "kernel_intro", "merge_tournament_pair", "merge_resort_pair",
    "merge_bound_sweep_dup3", "exact_quantiles_lineitem", "join_star_revenue", "agg_pricing_summary", "win_global_running_sum", "distinct_by_sort",
)


def main() -> None:
    from evensort import bench, catalog

    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), int(os.environ.get("BENCH_CPUS", "8"))
    spark = session(cpus)
    every = catalog.queries()
    bench.once(lambda: every["sort_exact_dup3"](spark, sf_dir))  # warm-up
    times = {}
    for name in HEADLINE:
        times[name] = round(bench.once(lambda name=name: every[name](spark, sf_dir)), 3)
    runs, copies = int(os.environ.get("BENCH_RUNS", "1")), int(os.environ.get("BENCH_COPIES", "1"))
    both, rules = ("uniform_int", "dup3"), ("exact", "stable_snap")
    claims = bench.claims(spark, sf_dir)
    # means after a run that warms up; more copies (67 make 10^7 rows) and the study's steps on demand
    means = bench.fig_time(spark, sf_dir, cpus, rules, both, runs)
    full = "BENCH_FULL" in os.environ
    large = bench.fig_time(spark, sf_dir, cpus, rules, both, runs, copies) if copies > 1 else {}
    steps = bench.fig_time(spark, sf_dir, cpus, ("exact", "regular", "stable_snap"), both, runs, stepwise=True) if full else {}
    sorters = bench.fig_block_sorters(spark, sf_dir, cpus, ("intro", "three_way", "branchless"), both, runs) if full else {}
    mergers = bench.fig_mergers(spark, sf_dir, cpus, ("tournament", "pairs", "binary_heap", "resort"), ("uniform_int", "almost_sorted"), runs) if full else {}
    out = {"metric": "total seconds of headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf"), "cpus": cpus}
    out["merge_bound_dup3"] = claims
    rounded = lambda d: {k: round(v, 3) for k, v in d.items()}
    ratio = lambda d: {s: round(d[f"stable_snap/{s}"] / d[f"exact/{s}"], 3) for s in ("uniform_int", "dup3") if f"exact/{s}" in d}
    out["mean_sec"], out["mean_sec_branchless_tournament"], out[f"mean_sec_times_{copies}"] = rounded(means), rounded(steps), rounded(large)
    out["mean_sec_block_sorters"], out["mean_sec_mergers"] = rounded(sorters), rounded(mergers)
    out["speed_exact_over_stable_snap"] = {"mean": ratio(means), "branchless_tournament": ratio(steps), f"times_{copies}": ratio(large)}
    out["kernel_work"] = {k: {c: w[c] for c in ("comparisons", "moves", "branches", "fallbacks")} for k, w in {**bench.kernel_work(), **bench.merger_work()}.items()}
    print(json.dumps(out), flush=True)
    spark.stop()


if __name__ == "__main__":
    began = time.time()
    main()
    print(f"bench took {time.time() - began:.0f} s", file=sys.stderr)
