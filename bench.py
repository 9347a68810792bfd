"""Times the headline queries and prints one JSON line. BENCH_SF_DIR: the tables; BENCH_CPUS: cores; BENCH_ROWS: rows a side of the generated pair.

Beside seconds and errors it gives what each run shuffled (MB), its jobs, and the points that its summaries store. The ``big_*`` runs compare
two generated samples that are large enough to show what sketches spare.
"""

from __future__ import annotations

import json
import os
import shutil
import sys
import tempfile
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

from driftks.operators import exact, kstest, workloads  # noqa: E402
from driftks.sketch import direct, kll  # noqa: E402
from driftks.sources import load  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
ROWS = int(os.environ.get("BENCH_ROWS", "5000000"))


def main() -> None:
    shared = tempfile.mkdtemp(prefix="bench-")  # one machine: driver and executors share it
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "16g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", f"file://{shared}")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    price = workloads.pair("price", spark, SF_DIR)
    prices = load(spark, SF_DIR, "lineitem").where("l_returnflag in ('R', 'N')")
    big = workloads.sides(workloads.full_size("w3", spark, 1, (ROWS, ROWS), "bench"))
    test = lambda *pair, **how: kstest.two_sample_test(*pair, phi=0.002, **how).first()
    runs = {
        "exact_window": lambda: exact.exact_distance(*price, "window").first(),
        "exact_range": lambda: exact.exact_distance(*price, "range").first(),
        "exact_refine": lambda: exact.exact_distance(*price, "refine").first(),
        "exact_histogram_join": lambda: exact.exact_distance(*price, "histogram_join").first(),
        "approx_unit_slope": lambda: test(*price),
        "approx_balanced": lambda: test(*price, split="balanced"),
        "approx_summary": lambda: test(*price, split="balanced", engine="summary"),
        "approx_one_scan": lambda: kstest.one_scan_test(prices, F.col("l_extendedprice"), F.col("l_returnflag") == "R", phi=0.002).first(),
        "direct_sketch": lambda: direct.direct_sketch_test(*price, 0.002).first(),
        "kll": lambda: kll.direct_kll_test(*price).first(),
        "big_exact_range": lambda: exact.exact_distance(*big, "range").first(),
        "big_approx_unit_slope": lambda: test(*big),
        "big_approx_balanced": lambda: test(*big, split="balanced"),
    }
    store = spark.sparkContext._jsc.sc().statusStore()

    def shuffled() -> float:
        found = store.executorList(False)
        return sum(found.apply(i).totalShuffleWrite() for i in range(found.size())) / 1e6

    test(*price, split="balanced")  # compile and warm the scan
    seconds, distances, shuffles, jobs, points = {}, {}, {}, {}, {}
    for name, run in runs.items():
        spark.sparkContext.setJobGroup(name, name)
        before, began = shuffled(), time.perf_counter()
        row = run().asDict()
        seconds[name] = round(time.perf_counter() - began, 3)
        shuffles[name] = round(shuffled() - before, 3)
        jobs[name] = len(spark.sparkContext.statusTracker().getJobIdsForGroup(name))
        distances[name] = next(row[c] for c in ("d", "d_hat", "d_sketch") if c in row)
        points[name] = sum(row.get(c) or 0 for c in ("a_x", "a_y", "points_x", "points_y"))
    true = lambda name: distances["big_exact_range" if name.startswith("big") else "exact_range"]
    out = {"metric": "headline_total", "value": round(sum(v for k, v in seconds.items() if not k.startswith("big")), 3), "unit": "sec", "queries": seconds, "errors": {k: round(abs(d - true(k)), 6) for k, d in distances.items()}}
    print(json.dumps(out | {"shuffle_mb": shuffles, "jobs": jobs, "points": points, "big_rows": 2 * ROWS, "sf": SF_DIR.rstrip("/").rsplit("sf", 1)[-1]}))
    spark.stop()
    shutil.rmtree(shared, ignore_errors=True)


if __name__ == "__main__":
    main()
