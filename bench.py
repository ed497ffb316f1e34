"""Runs the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS] and prints one JSON line.

Each query has $BENCH_LIMIT seconds (default 60); one that is stopped there counts with its limit and is listed as over_limit.
Beside the seconds the line tells rows, megabytes shuffled and spilled, the phases of the general method, and seconds by cycle length.
"""

from __future__ import annotations

import json
import os
import sys
import threading
import time

from pyspark.sql import SparkSession

HEADLINES = [
    "triangle_cust_supp_part", "triangle_heavy_probe", "pairwise_catalyst", "triangle_handoff", "triangle_embeddings", "abo4_lineitem", "abo_bad_n4", "anchored_worked_example",
    "anchored_triangle", "grid_triangle", "cycle4_nation", "cycle5_region", "cycle7_orders", "graph_star_cycle", "fd_expand_orders", "relaxed_r1", "geo_reconstruct", "lp_triangle_bound",
]


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    limit = float(os.environ.get("BENCH_LIMIT", "60"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(max(8, 2 * int(cpus))) if cpus.isdigit() else "16")
        .config("spark.driver.memory", "4g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    from coverjoin import storage, workloads
    from coverjoin.operators import metrics

    def timed(run) -> tuple[float, object]:
        """Seconds and result; None where the limit was reached."""
        stopped = threading.Event()

        def stop():
            stopped.set()
            spark.sparkContext.cancelAllJobs()

        timer = threading.Timer(limit, stop)
        timer.start()
        t, got = time.perf_counter(), None
        try:
            got = run()
        except Exception:
            if not stopped.is_set():
                raise
        finally:
            timer.cancel()
        return round(time.perf_counter() - t, 2), got

    spark.range(1000).selectExpr("sum(id)").collect()
    times, rows, moved, over = {}, {}, {}, []
    for name in HEADLINES:
        seen = {}

        def run(name=name, seen=seen):
            seen.update(metrics.moved(spark, lambda: seen.update(n=workloads.QUERIES[name](spark, sf).count())))
            return seen.pop("n")

        times[name], rows[name] = timed(run)
        moved[name] = [seen.get("shuffle_mb"), seen.get("spill_mb")]
        if rows[name] is None:
            over.append(name)
        storage.release(spark)
    extra = {"phases_anchored_triangle": timed(lambda: {k: round(v, 2) for k, v in metrics.phases(workloads.w01(spark, sf)).items()})[1]}
    extra["cycle_seconds"] = {n: times[k] for n, k in ((4, "cycle4_nation"), (5, "cycle5_region"), (7, "cycle7_orders"))}
    storage.release(spark)
    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(times.values()), 2), "unit": "sec", "queries": times, "rows": rows, "shuffle_spill_mb": moved, "over_limit": over, **extra, "sf": sf.rstrip("/").rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
