"""The experiments: methods over graphs, as trace tables and the measures on them."""

from __future__ import annotations

import time
from statistics import median

from pyspark.sql import DataFrame, SparkSession

from minlabel import schemas
from minlabel.graph import Graph
from minlabel.plans import measures
from minlabel.plans.engine import connected_components
from minlabel.workloads import WORKLOADS, lattice

COMPARED = ("orderm", "order2", "low_then_high", "alternate", "sync2", "hook_compress", "order1", "union_find")
IN_PLACE = ("orderm", "order2", "low_then_high", "alternate")
LOW_ONLY = ("order1", "bfs", "label_propagation")
#: In-place rounds as they are counted: one sweep of every block, of which there are several, and no block is settled at once.
#: Synchronous rounds, which give the same labels wherever they are made, are made in one task on graphs of up to 8 million edges, and so are the hops along up to 8 million pointers of in-place ones.
LOCAL = {"local_edges": 1 << 23}
COUNTED = {"local_sweeps": 1, **LOCAL}


def runs(name: str, method: str) -> bool:
    """Whether the method is run on the graph: those that spread labels by one edge a round take as many rounds as the diameter has edges, thousands on paths and chains."""
    return method not in LOW_ONLY or WORKLOADS[name].low


_runs: dict[tuple, list] = {}
_graphs: dict[tuple, Graph] = {}


def built(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """A graph, made once in an application: all methods read what was written of it."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _graphs:
        _graphs[key] = WORKLOADS[name].build(spark, sf_dir).kept()
    return _graphs[key]


def rounds_of(spark: SparkSession, sf_dir: str, name: str, method: str) -> list[tuple]:
    """The trace of a method on a graph, made once in an application; all measures are of the same runs, which are few rows each."""
    key = (spark.sparkContext.applicationId, sf_dir, name, method)
    if key not in _runs:
        _runs[key] = connected_components(built(spark, sf_dir, name), method, **(COUNTED if method in IN_PLACE else LOCAL)).trace
    return _runs[key]


def traces(spark: SparkSession, sf_dir: str, graphs: list[str], methods: tuple[str, ...] = COMPARED) -> DataFrame:
    """Rounds of every method on every graph that it is run on."""
    rows = [row for name in graphs for m in methods if runs(name, m) for row in rounds_of(spark, sf_dir, name, m)]
    return spark.createDataFrame(rows, schemas.TRACE)


def timed(g, method: str, times: int = 3, **options) -> float:
    """Median seconds of some runs on a graph that is ready."""
    took = []
    for _ in range(times):
        began = time.perf_counter()
        connected_components(g, method, **options)
        took.append(time.perf_counter() - began)
    return median(took)


def family_times(spark: SparkSession, sizes: range, methods: tuple[str, ...] = ("order2", "orderm", "low_then_high", "alternate", "sync2", "hook_compress", "union_find"), permute: bool = True, times: int = 1) -> DataFrame:
    """Seconds on triangulations of growing size."""
    rows = []
    for k in sizes:
        g = lattice(spark, k, permute)
        g.prepared(int(spark.conf.get("spark.sql.shuffle.partitions")))
        rows += [(g.name, m, 1 << k, timed(g, m, times)) for m in methods]
    return spark.createDataFrame(rows, "graph string, method string, n bigint, seconds double")


def growth(spark: SparkSession, sizes: range, **options) -> DataFrame:
    return measures.growth(family_times(spark, sizes, **options))


def core_times(spark: SparkSession, name: str, sf_dir: str, cores: tuple[int, ...] = (1, 2, 4, 8), methods: tuple[str, ...] = ("order2", "union_find", "hook_compress")) -> DataFrame:
    """Seconds with the work dealt to so many tasks at a time: with fewer partitions than the machine has cores, the others idle. The session's own number of partitions is put back."""
    kept, rows = spark.conf.get("spark.sql.shuffle.partitions"), []
    try:
        for n in cores:
            spark.conf.set("spark.sql.shuffle.partitions", str(n))
            g = WORKLOADS[name].build(spark, sf_dir)
            g.raw = g.raw.coalesce(n)
            rows += [(name, m, n, timed(g, m, 1, num_partitions=n)) for m in methods]
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", kept)
    return spark.createDataFrame(rows, "graph string, method string, cores int, seconds double")


def speedups(spark: SparkSession, sf_dir: str, graphs: list[str], base: str = "hook_compress", methods: tuple[str, ...] = COMPARED) -> DataFrame:
    return measures.speedups(measures.iterations(traces(spark, sf_dir, graphs, methods)), base)


def communication(spark: SparkSession, sf_dir: str, graphs: list[str], methods: tuple[str, ...] = COMPARED) -> DataFrame:
    """Rows sent by each method: of synchronous ones from their rounds and the graph's size, of in-place ones what their rounds left."""
    rows = []
    for name in graphs:
        g = WORKLOADS[name].build(spark, sf_dir)
        n, m = g.vertices.count(), g.own_edges().count()
        for method in methods:
            if runs(name, method):
                trace = rounds_of(spark, sf_dir, name, method)
                rows.append((name, method, len(trace), measures.exchange_rows(method, n, m, trace)))
    return spark.createDataFrame(rows, "graph string, method string, iterations int, rows_sent bigint")


ABLATED = (
    ("sync2", {}), ("order2", {"update": "sync", "early_check": "off"}), ("order2", {"update": "sync", "early_check": "fused"}), ("order2", {"update": "sync", "early_check": "eager"}), ("order2", {"retire": True}),
    ("chained", {}), ("block_async", {}), ("order2", {"local_sweeps": 1}), ("order2", {"local_sweeps": 0}), ("order2", {}),
)


def ablation(spark: SparkSession, sf_dir: str, graphs: list[str], variants=ABLATED) -> DataFrame:
    """What each optimization does: synchronous, chained, block-asynchronous and in-place updates, and the early check off, fused and eager."""
    rows = []
    for name in graphs:
        g = WORKLOADS[name].build(spark, sf_dir)
        for method, options in variants:
            began = time.perf_counter()
            r = connected_components(g, method, **options)
            rows.append((name, method, ", ".join(f"{k}={v}" for k, v in options.items()), r.iterations, r.edge_passes, time.perf_counter() - began))
    return spark.createDataFrame(rows, "graph string, method string, options string, iterations int, edge_passes int, seconds double")
