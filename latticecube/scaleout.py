"""Scale-out of maintenance (W7): the same refresh with more and more cores, each in a process of its own.

``python -m latticecube.scaleout SF_DIR [CORES,CORES,…]`` prints one JSON line: a delta of twenty percent, MEDIAN by recomputation and SUM by incremental
maintenance, both from a store.  On one machine cores stand for nodes; slots stay the same, so that each run does the same work.
"""

from __future__ import annotations

import json
import subprocess
import sys

SLOTS = 24
DELTA = 20
#: Function and manner of each curve.
CURVES = {"median": "recompute_reuse", "sum": "incremental_reuse"}


def run_one(sf_dir: str, cores: int) -> dict[str, float]:
    """Refresh seconds of each curve in this process: the least of three, the first of which warms it up."""
    from pyspark.sql import SparkSession

    from latticecube import workloads as W

    spark = (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", str(SLOTS))
        .config("spark.driver.memory", "6g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    try:
        rows, aggs = W.lineitem(spark, sf_dir), {"median": W.MEDIAN_QTY, "sum": W.SUM_QTY}
        out = {}
        for fn, manner in CURVES.items():
            out[fn] = W.w5_w6_maintenance(rows, aggs[fn], [manner], [DELTA], repeats=3)[0]["refresh_s"]
        return out
    finally:
        spark.stop()


def w7_scaleout(sf_dir: str, cores: list[int]) -> dict[str, list[dict]]:
    """The curve of each function: seconds, speed-up and efficiency by cores."""
    from latticecube import metrics

    times = {}
    for c in cores:
        done = subprocess.run([sys.executable, "-m", "latticecube.scaleout", "--one", sf_dir, str(c)], capture_output=True, text=True, check=True)
        times[c] = json.loads(done.stdout.strip().splitlines()[-1])
    return {fn: metrics.scaleup([(c, times[c][fn]) for c in cores]) for fn in CURVES}


def main(args: list[str]) -> None:
    if args[0] == "--one":
        print(json.dumps(run_one(args[1], int(args[2]))))
    else:
        cores = [int(c) for c in args[1].split(",")] if len(args) > 1 else [1, 2, 4, 8]
        print(json.dumps(w7_scaleout(args[0], cores)))


if __name__ == "__main__":
    main(sys.argv[1:])
