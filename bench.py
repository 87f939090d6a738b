"""Headline times: one JSON line.  BENCH_SF_DIR, BENCH_CPUS and BENCH_REPEATS set the tables, cores and passes (least time counts, means beside it).

All measures run once in a pass; a further pass starts only if it should end within BENCH_BUDGET seconds.
"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    repeats, budget, born = int(os.environ.get("BENCH_REPEATS", "3")), float(os.environ.get("BENCH_BUDGET", "900")), time.perf_counter()
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(3 * int(cpus)))
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "12g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from latticecube import metrics
    from latticecube import workloads as W
    from latticecube.operators import maintain
    from latticecube.operators import materialize as M

    # the given table is one file of one row group, which one task reads: lay it out in files once, as a large table is
    laid = W.files.scratch_dir(spark)
    W.lineitem(spark, sf_dir).repartition(2 * int(cpus)).write.parquet(laid)
    rows = spark.read.parquet(laid)
    sums, medians = W.spec4(W.SUM_QTY), W.spec4(W.MEDIAN_QTY)
    warm = W.lineitem(spark, os.path.join(os.path.dirname(sf_dir.rstrip("/")), "sf0.001"))
    for spec in (sums, medians):
        metrics.drain(M.materialize(warm, spec).df)

    taken: dict[str, list[float]] = {}
    shuffled: dict[str, int] = {}
    plan: list[tuple] = []

    def measure(name, run, prepare=lambda: None):
        plan.append((name, run, prepare))

    def one_pass() -> float:
        started = time.perf_counter()
        for name, run, prepare in plan:
            ready = prepare()
            with metrics.watch(spark) as seen:
                began = time.perf_counter()
                run() if ready is None else run(ready)
                taken.setdefault(name, []).append(time.perf_counter() - began)
            shuffled[name] = seen.shuffle_cost()["records"]
        return time.perf_counter() - started

    for fn, spec in (("sum", sums), ("median", medians)):
        measure(f"cube_{fn}_shared", lambda spec=spec: metrics.drain(M.materialize(rows, spec).df))
        measure(f"cube_{fn}_per_cuboid", lambda spec=spec: W.run_per_cuboid(rows, spec))
        measure(f"cube_{fn}_unshared", lambda spec=spec: metrics.drain(M.materialize(rows, spec, method="fanout_unshared").df))
        measure(f"cube_{fn}_native", lambda spec=spec: metrics.drain(M.materialize(rows, spec, method="native_cube").df))

    def cached(spec, kind):
        cube = maintain.materialize_cached(rows, spec, W._new_store(spark, spec), kind)
        if kind == "input":  # a view cache is itself the published views
            W.published(cube.df)

    for fn, spec, kind in (("sum", sums, "view"), ("median", medians, "input")):
        measure(f"cube_{fn}_published", lambda spec=spec: W.published(M.materialize(rows, spec).df))
        measure(f"cube_{fn}_cached", lambda spec=spec, kind=kind: cached(spec, kind))
    for p in (5, 100):
        base, delta = W.parts_as_files(rows, p, 2 * int(cpus))
        for fn, spec, manners in (("sum", sums, ("incremental", "recompute")), ("median", medians, ("recompute",))):
            for manner in manners:
                for how in ("reuse", "reload"):
                    measure(f"refresh_{fn}_{manner}_{how}_{p}", lambda run: run(), prepare=W.one_refresh(spec, f"{manner}_{how}", base, delta))
    last, spent, passes = one_pass(), time.perf_counter() - born, 1
    while passes < repeats and spent + last <= budget:
        last, spent, passes = one_pass(), time.perf_counter() - born, passes + 1
    out = {name: round(min(times), 3) for name, times in taken.items()}
    means = {name: round(sum(times) / len(times), 3) for name, times in taken.items()}
    ratio = lambda a, b: round(out[a] / out[b], 2)
    ratios = {f"{fn}_{m}_over_shared": ratio(f"cube_{fn}_{m}", f"cube_{fn}_shared") for fn in ("sum", "median") for m in ("per_cuboid", "unshared", "native")}
    ratios |= {f"{fn}_cache_overhead": round(ratio(f"cube_{fn}_cached", f"cube_{fn}_published") - 1, 2) for fn in ("sum", "median")}
    for p in (5, 100):
        ratios |= {f"{k}_reload_over_reuse_{p}": ratio(f"refresh_{k}_reload_{p}", f"refresh_{k}_reuse_{p}") for k in ("sum_incremental", "sum_recompute", "median_recompute")}
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "sf": sf_dir.rstrip("/").rsplit("sf", 1)[-1], "ratios": ratios, "passes": passes, "means": means, "shuffled_records": shuffled}))


if __name__ == "__main__":
    main()
