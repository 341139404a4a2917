"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

One query warms the session up and isn't counted. ``arms`` has, for one use case, both
arms' total milliseconds by phase, the share spent on messages, and the remote messages.
"""

from __future__ import annotations

import json
import os
import shutil
import sys
import tempfile
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

HEADLINE = [
    "lattice_edges", "neighbour_histogram", "step_once", "adapt_history_t4", "adapt_history", "w4_convergence_t4", "w4_convergence", "message_cost", "cut_matrix", "w6_influence", "w6_mention_arms",
    "w6_throughput", "w7_window_edges", "w7_cuts_weekly_static", "tissue_t3", "apply_changes",
]


def main() -> None:
    from pyspark.sql import SparkSession

    cpus, sf = os.environ.get("BENCH_CPUS", "8"), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    folder = tempfile.mkdtemp(prefix="bench-checkpoints-")  # one machine, so its folder is shared
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "16g")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.checkpoint.dir", folder)
        .config("spark.cleaner.referenceTracking.cleanCheckpoints", "true")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from graphdrift.plans import registry, workloads

    found = registry.queries()
    found["degree_profile"](spark, sf).write.format("noop").mode("overwrite").save()
    times = {}
    for name in HEADLINE:
        began = time.time()
        found[name](spark, sf).write.format("noop").mode("overwrite").save()
        times[name] = round(time.time() - began, 3)
        print(name, times[name], file=sys.stderr)
    arms = {r["arm"]: {k: round(v, 3) if isinstance(v, float) else v for k, v in r.asDict().items() if k != "arm"} for r in workloads.arms_summary(spark, sf, "mentions", 6).collect()}
    print(arms, file=sys.stderr)
    spark.stop()
    shutil.rmtree(folder, ignore_errors=True)
    print(json.dumps({"metric": "total seconds of headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": sf, "arms": arms}))


if __name__ == "__main__":
    main()
