"""Headline queries, timed: prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

METHODS = ("order2", "orderm", "low_then_high", "alternate", "sync2", "hook_compress", "union_find", "block_async")
FAMILY = ("order2", "orderm", "low_then_high", "alternate", "union_find", "hook_compress")
GRAPHS = ("order_part", "customer_day", "doc_line")


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("minlabel-bench").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", cpus)
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from minlabel.plans.engine import connected_components
    from minlabel.session import stored
    from minlabel.workloads import WORKLOADS, lattice

    seconds: dict[str, float] = {}
    rounds: dict[str, int] = {}

    def timed(name, g, method):
        began = time.perf_counter()
        result = connected_components(g, method)
        result.labels.count()
        seconds[name], rounds[name] = round(time.perf_counter() - began, 3), result.iterations

    warm = WORKLOADS["fk_hierarchy"].build(spark, sf_dir)
    for m in METHODS:
        connected_components(warm, m)
    for name in GRAPHS:
        g = WORKLOADS[name].build(spark, sf_dir)
        g.prepared(int(cpus))
        g.raw = stored(g.raw)  # the methods are timed, not the making of the graph
        for m in METHODS:
            timed(f"{m}_{name}", g, m)
    for k in (12, 16):  # growth over sizes of one family
        g = lattice(spark, k, True)
        g.prepared(int(cpus))
        g.raw = stored(g.raw)
        for m in FAMILY:
            timed(f"{m}_lattice{k}", g, m)
    speed = {m: round(sum(seconds[f"hook_compress_{g}"] / seconds[f"{m}_{g}"] for g in GRAPHS) / len(GRAPHS), 2) for m in METHODS}
    against = {m: round(sum(seconds[f"union_find_{g}"] / seconds[f"{m}_{g}"] for g in GRAPHS) / len(GRAPHS), 2) for m in METHODS}
    growth = {m: round(seconds[f"{m}_lattice16"] / seconds[f"{m}_lattice12"], 2) for m in FAMILY}
    mean = {m: round(sum(rounds[f"{m}_{g}"] for g in GRAPHS) / len(GRAPHS), 2) for m in METHODS}
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf"), "rounds": rounds, "mean_rounds": mean, "mean_speedup_over_hook_compress": speed, "mean_speedup_over_union_find": against, "growth_of_time_for_16_times_the_size": growth}))


if __name__ == "__main__":
    main()
