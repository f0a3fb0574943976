"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``python bench.py --workloads`` runs the experiment workloads instead and prints
one JSON line for each row.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

HEADLINE = (
    "bf_nn_line4", "exact_nn_line4", "oneshot_nn_line4", "bf_nn_orders2", "exact_nn_orders2", "oneshot_nn_orders2", "exact_nn_events3", "exact_nn_lift74",
    "exact_nn_rp8", "exact_knn_line4", "exact_range_line4", "cover_exact_sizes", "exact_recursive", "nettree_nn", "kdtree_nn", "stream_exact",
)


def session() -> SparkSession:
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "12g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def headline(spark: SparkSession, sf_dir: str) -> dict:
    from nearfield import catalogue

    known, seconds = catalogue.queries(), {}
    for name in HEADLINE:
        began = time.perf_counter()
        known[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.perf_counter() - began, 3)
    return seconds


def workloads(spark: SparkSession, sf_dir: str) -> None:
    from nearfield.plans import workloads as w

    def tell(kind: str, rows) -> None:
        for row in rows if isinstance(rows, list) else [rows]:
            print(json.dumps({"workload": kind} | {k: round(v, 4) if isinstance(v, float) else v for k, v in row.items()}), flush=True)

    # About 10,000 queries where the table has as many points to spare.
    wide = {n: 59 for n in ("line4", "line8", "lift21", "lift54", "lift74", "lift78")}
    sets = wide | {"orders2": 15, "events3": 10, "part2": 10, "rp4": 4, "rp8": 4, "rp16": 4, "rp32": 4, "emb64": 4}
    only = sys.argv[sys.argv.index("--workloads") + 1 :]
    jobs = {
        "speedup": lambda: [w.speedup(spark, sf_dir, n, every=e) for n, e in sets.items()],
        "oneshot_sweep": lambda: [r for n in ("line4", "orders2", "events3", "rp8") for r in w.sweep_oneshot(spark, sf_dir, n, every=max(sets[n], 50) if n != "rp8" else 4)],
        "tuned": lambda: [w.tuned_oneshot(spark, sf_dir, n, every=e) for n, e in (("orders2", 100), ("events3", 100), ("line4", 590), ("rp4", 4))],
        "tree": lambda: [w.tree_comparison(spark, sf_dir, n, every=sets[n]) for n in ("orders2", "events3", "rp4", "rp8", "rp16", "rp32")],
        "sensitivity": lambda: [r for n in ("line4", "lift74", "orders2") for r in w.sensitivity(spark, sf_dir, n, every=sets[n])],
    }
    for kind, job in jobs.items():
        if not only or kind in only:
            tell(kind, job())


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = session()
    if "--workloads" in sys.argv:
        workloads(spark, sf_dir)
        return
    seconds = headline(spark, sf_dir)
    sf = os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")
    print(json.dumps({"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": float(sf) if sf.replace(".", "", 1).isdigit() else sf}))


if __name__ == "__main__":
    main()
