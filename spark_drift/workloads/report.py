"""Prints the planted-drift comparison as a table: ``python -m spark_drift.workloads.report``.

Environment: ``REPORT_ROWS`` a stream (60,000), ``REPORT_RUNS`` (10), ``REPORT_KINDS`` (mean,spread),
``REPORT_TUNE_SEGMENTS`` (all 100), ``REPORT_WINDOWS`` (100,200), ``REPORT_STEP`` as a share of the window (0.2),
``REPORT_LEAST`` change as a share of the largest (1), ``REPORT_TUNE_RUNS`` (1).
"""

from __future__ import annotations

import os
import time

from pyspark.sql import SparkSession

from spark_drift.workloads import detectors


def main() -> None:
    cores = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", 32).config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    rows, runs = int(os.environ.get("REPORT_ROWS", "60000")), int(os.environ.get("REPORT_RUNS", "10"))
    windows = [int(w) for w in os.environ.get("REPORT_WINDOWS", "100,200").split(",")]
    tune = int(os.environ.get("REPORT_TUNE_SEGMENTS", "100"))
    share, least = float(os.environ.get("REPORT_STEP", "0.2")), float(os.environ.get("REPORT_LEAST", "1"))
    tuning = tuple(range(1000, 1000 + int(os.environ.get("REPORT_TUNE_RUNS", "1"))))
    print("| change | method | detected | late | missed | false | setting | inside the grid |\n|---|---|---|---|---|---|---|---|")
    for kind in os.environ.get("REPORT_KINDS", "mean,spread").split(","):
        began = time.time()
        report = tuple(range(2000, 2000 + runs))
        found = detectors.compare(spark, kind, None, rows, 100, tuning, report, tune, windows, share, least)
        for r in sorted(found.collect(), key=lambda r: -r["detected"]):
            counts = " | ".join(f"{r[c]:.1f}" for c in ("detected", "late", "missed", "false_reports"))
            print(f"| {kind} | {r['method']} | {counts} | {r['setting']} | {r['inside']} |", flush=True)
        print(f"{kind}: {time.time() - began:.0f} s", flush=True)


if __name__ == "__main__":
    main()
