"""Costs and qualities of runs: iterations, times, growth, speedups, the iteration bound, components and degrees."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from minlabel.graph import Graph, joined_to
from minlabel.operators import mapping
from minlabel.session import stored

# Rows that the exchanges of a synchronous round carry, in units of directed edges (E) and of vertices (V): of the edge
# aggregate, of the labels' join, and of what a method sends beside them.
EXCHANGES = {"hook_compress": (2, 4), "block_async": (1, 4), "label_propagation": (2, 1), "bfs": (1, 1)}


def order_exchanges(order: int) -> tuple[int, int]:
    """Of a synchronous round of an order: log2 of it pointer tables, of three exchanges each (used, moving, looked up), and as many upward aggregates."""
    doublings = max(order.bit_length() - 1, 0)
    return 1, 1 + 4 * doublings


def iteration_bound(diameter: int) -> int:
    """Rounds of order 2 or more that a graph of this diameter takes at most."""
    return math.ceil(math.log(diameter, 1.5)) + 1 if diameter > 1 else 2


def iterations(trace: DataFrame) -> DataFrame:
    return trace.groupBy("graph", "method").agg(F.max("iteration").alias("iterations"), F.sum("seconds").alias("seconds"))


def mean_iterations(trace: DataFrame) -> DataFrame:
    return iterations(trace).groupBy("method").agg(F.avg("iterations").alias("mean_iterations"))


def compare_iterations(trace: DataFrame, a: str, b: str) -> DataFrame:
    """Numbers of graphs on which a takes as many, more and fewer rounds than b, and the most that a saves."""
    by = iterations(trace).groupBy("graph").pivot("method", [a, b]).agg(F.max("iterations"))
    d = F.col(a) - F.col(b)
    return by.agg(F.count_if(d == 0).alias("equal"), F.count_if(d > 0).alias("more"), F.count_if(d < 0).alias("fewer"), F.max(-d).alias("most_saved"))


def order_relation(trace: DataFrame, high: str = "orderm", two: str = "order2", one: str = "order1") -> DataFrame:
    """For each graph whether higher orders take no more rounds."""
    by = iterations(trace).groupBy("graph").pivot("method", [high, two, one]).agg(F.max("iterations"))
    return by.select("graph", (F.coalesce(F.col(high) <= F.col(two), F.lit(True)) & F.coalesce(F.col(two) <= F.col(one), F.lit(True))).alias("holds"))


def growth(times: DataFrame) -> DataFrame:
    """times(method, n, seconds): how much longer the largest takes than the smallest."""
    return times.groupBy("method").agg((F.max_by("seconds", "n") / F.min_by("seconds", "n")).alias("growth"), (F.max("n") / F.min("n")).alias("size_ratio"))


def speedups(times: DataFrame, base: str) -> DataFrame:
    """times(graph, method, seconds): mean speedup over the base, and graphs on which it is faster."""
    own = times.where(F.col("method") == base).select("graph", F.col("seconds").alias("base_seconds"))
    ratio = F.col("base_seconds") / F.col("seconds")
    return times.where(F.col("method") != base).join(own, "graph").groupBy("method").agg(F.avg(ratio).alias("mean_speedup"), F.count_if(ratio > 1).alias("wins"), F.count("*").alias("graphs"))


def exchange_rows(method: str, n: int, m: int, trace: list[tuple]) -> int:
    """Rows that the rounds of a run send, before combining. In-place rounds send a pointer of each id that changes and the edges that are left (changed, violations of the trace), once by id and once more in the end; the first one no other edges."""
    if method == "union_find":  # every forest holds an id once, and is sent once for each merge
        return 2 * n
    if any(row[6] is None for row in trace) and method not in EXCHANGES:  # in place: the first round counts no edges
        return sum(2 * row[4] + row[5] for row in trace) + n
    total = 0
    for row in trace:
        e, v = EXCHANGES.get(method) or order_exchanges(row[3])
        total += e * 2 * m + v * n
    return total


def work_depth(m: int, rounds: int, cores: int) -> float:
    return m / cores * rounds


def component_sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy(F.col("label").alias("component")).agg(F.count("*").alias("size"), F.min("id").alias("min_id"), F.max("id").alias("max_id"))


def component_histogram(labels: DataFrame) -> DataFrame:
    return component_sizes(labels).groupBy("size").agg(F.count("*").alias("components"))


def degrees(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("id")).groupBy("id").agg(F.count("*").alias("degree"))


def degree_histogram(edges: DataFrame) -> DataFrame:
    return degrees(edges).groupBy("degree").agg(F.count("*").alias("vertices"))


def graph_stats(g: Graph, sweep: bool = True) -> dict:
    """n and m of the edges, degrees, and a lower bound of the diameter."""
    d = degrees(g.edges).agg(F.count("*").alias("n"), F.max("degree").alias("most"), F.avg("degree").alias("mean")).first()
    return {"n": d.n, "m": g.edges.count(), "max_degree": d.most or 0, "mean_degree": d.mean or 0.0, "diameter_lb": diameter(g) if sweep and d.n else 0}


def diameters(g: Graph, labels: DataFrame, most: int = 10_000) -> DataFrame:
    """component and a lower bound of its diameter, by two sweeps of breadth-first search in all components at once: from the smallest id, then from a vertex that is farthest from it. A component that a sweep has not left after most hops is an error."""
    first = _sweep(g, labels.where("id = label").select("id", F.col("label").alias("component")), most)
    return _sweep(g, first.select("id", "component"), most).select("component", "diameter")


def diameter(g: Graph, most: int = 10_000) -> int:
    """Lower bound of the largest diameter of a component."""
    from minlabel.plans.engine import connected_components

    return diameters(g, connected_components(g, "order2").labels, most).agg(F.max("diameter")).first()[0] or 0


def exact_diameters(g: Graph, labels: DataFrame, most_vertices: int = 5_000) -> DataFrame:
    """component and its diameter: distances between all vertices of each component, by a search from every vertex at once. For graphs of at most most_vertices."""
    if g.vertices.count() > most_vertices:
        raise ValueError(f"exact diameters are for graphs of at most {most_vertices} vertices")
    directed = g.prepared(int(g.edges.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    seen = frontier = stored(labels.select("id", F.col("id").alias("start"), F.col("label").alias("component"), F.lit(0).alias("depth")))
    depth = 0
    while not frontier.isEmpty():
        depth += 1
        near = joined_to(directed, frontier.select(F.col("id").alias("src"), "start", "component")).select(F.col("dst").alias("id"), "start", "component").distinct()
        frontier = stored(near.join(seen.select("id", "start"), ["id", "start"], "left_anti").withColumn("depth", F.lit(depth)))
        seen = stored(seen.unionByName(frontier))
    return seen.groupBy("component").agg(F.max("depth").alias("diameter"))


def _sweep(g: Graph, starts: DataFrame, most: int) -> DataFrame:
    """component, diameter (hops to the last vertex that is reached) and id (the smallest one at that distance), from one start in each component."""
    directed = g.prepared(int(g.edges.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    seen = frontier = stored(starts.withColumn("depth", F.lit(0)))
    for depth in range(1, most + 1):
        near = joined_to(directed, frontier.select(F.col("id").alias("src"), "component")).groupBy(F.col("dst").alias("id")).agg(F.first("component").alias("component"))
        frontier = stored(near.join(seen.select("id"), "id", "left_anti").withColumn("depth", F.lit(depth)))
        if frontier.isEmpty():
            break
        seen = stored(seen.unionByName(frontier)) if depth % 8 == 0 else seen.unionByName(frontier)
    else:
        raise ValueError(f"a component reaches over {most} hops; ask for more")
    return seen.groupBy("component").agg(F.max("depth").alias("diameter"), F.max_by("id", F.struct("depth", -F.col("id"))).alias("id"))


def violations(g: Graph, labels: DataFrame) -> DataFrame:
    """One row: edges across labels, labels over their id, labels that are no root; all 0 in a right result."""
    ends = g.edges.join(labels.select(F.col("id").alias("src"), F.col("label").alias("a")), "src").join(labels.select(F.col("id").alias("dst"), F.col("label").alias("b")), "dst")
    own = labels.join(labels.select(F.col("id").alias("label"), F.col("label").alias("root")), "label", "left")
    parts = [ends.select((F.col("a") != F.col("b")).cast("bigint").alias("x"), F.lit(0).alias("y"), F.lit(0).alias("z")), own.select(F.lit(0).alias("x"), (F.col("label") > F.col("id")).cast("bigint").alias("y"), (~F.col("root").eqNullSafe(F.col("label"))).cast("bigint").alias("z"))]
    return parts[0].unionByName(parts[1]).agg(F.coalesce(F.sum("x"), F.lit(0)).cast("bigint").alias("crossing_edges"), F.coalesce(F.sum("y"), F.lit(0)).cast("bigint").alias("larger_labels"), F.coalesce(F.sum("z"), F.lit(0)).cast("bigint").alias("labels_not_roots"))


def root_tree_sums(g: Graph, rounds: int = 20, applications: int = 1) -> list[tuple[int, int]]:
    """(round, sum of tree heights) of order 2 on a graph; on a path whose first vertex is the smallest, 1.5**(round - 1) times the sum stays under n."""
    n = int(g.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    directed, labels, out = g.prepared(n), mapping.init_labels(g.vertices), []
    for k in range(1, rounds + 1):
        before = labels
        for _ in range(applications):
            labels = stored(mapping.step(directed, labels, 2).select("id", "label"))
        heights = mapping.tree_heights(labels).agg(F.sum("height")).first()[0]
        out.append((k, int(heights)))
        if labels.join(before.withColumnRenamed("label", "old"), "id").where("label < old").isEmpty():
            break
    return out


def trace_deltas(trace: DataFrame) -> DataFrame:
    """Changes of each round next to those of the round before."""
    w = Window.partitionBy("graph", "method").orderBy("iteration")
    return trace.withColumn("before", F.lag("changed").over(w))
