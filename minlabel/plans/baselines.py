"""The methods that min-mapping is compared with, each in its own plan."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from minlabel.graph import Graph, joined_to
from minlabel.operators import kernels, mapping
from minlabel.plans.engine import ComponentResult, NotConverged, Options, in_one_task
from minlabel.session import collect_stored, discard, discard_collected, stored


def _guard(k: int, opts: Options, method: str) -> None:
    if k >= opts.max_iterations:
        raise NotConverged(f"{method} is not done after {k} iterations")


def hook_compress(graph: Graph, opts: Options, n: int) -> ComponentResult:
    """Hooking of parents, hooking of ends, and compressing, with a barrier after each; all read the labels from before the round."""
    if (made := in_one_task(graph, opts, lambda labels, src, dst, k: kernels.round_of_hooking(labels, src, dst), False)) is not None:
        labels, rounds = made
        edge_rows = 2 * graph.own_edges().count()
        return ComponentResult(labels, "hook_compress", len(rounds), 2 * len(rounds), True, [(graph.name, "hook_compress", r.k, 2, r.changed, None, 2 * edge_rows, r.seconds) for r in rounds])
    directed, labels = graph.prepared(n), stored(mapping.init_labels(graph.vertices))
    edge_rows, k, trace = directed.count(), 0, []
    while edge_rows:
        _guard(k, opts, "hook_compress")
        k, began = k + 1, time.perf_counter()
        made = collect_stored()
        far = stored(mapping.moved(labels.select("id", "label", F.col("label").alias("far")), "far", labels).select("id", "label", "far"))
        ends = joined_to(directed, far.select(F.col("id").alias("src"), "far"))
        parents = ends.join(labels.select(F.col("id").alias("dst"), F.col("label").alias("up")), "dst")
        hooked = stored(mapping.lower_labels(labels, parents.where("far < up").select(F.col("up").alias("id"), F.col("far").alias("c"))))
        hooked = stored(mapping.lower_labels(hooked, ends.select(F.col("dst").alias("id"), F.col("far").alias("c"))))
        out = stored(mapping.lower_labels(hooked, far.select("id", F.col("far").alias("c"))).join(labels.select("id", F.col("label").alias("before")), "id"))
        changed = out.where("label < before").count()
        discard_collected(made, out)
        discard(labels)
        labels = out
        trace.append((graph.name, "hook_compress", k, 2, changed, None, 2 * edge_rows, time.perf_counter() - began))
        if not changed:
            break
    return ComponentResult(labels.select("id", "label"), "hook_compress", k, 2 * k, True, trace)


def hook_compress_classic(graph: Graph, opts: Options, n: int) -> ComponentResult:
    """Roots hook on the smallest neighbouring root, then trees are compressed to stars."""
    directed, labels = graph.prepared(n), stored(mapping.init_labels(graph.vertices))
    edge_rows, k, trace = directed.count(), 0, []
    while edge_rows:
        _guard(k, opts, "hook_compress_classic")
        k, began = k + 1, time.perf_counter()
        ends = joined_to(directed, labels.select(F.col("id").alias("src"), F.col("label").alias("c"))).join(labels.select(F.col("id").alias("dst"), F.col("label").alias("up")), "dst")
        hooks = ends.where("c < up").select(F.col("up").alias("id"), "c")
        labels, before = stored(mapping.lower_labels(labels, hooks)), labels
        while not mapping.is_star_forest(labels):
            labels = stored(mapping.moved(labels, "label", labels).select("id", "label"))
        changed = labels.join(before.withColumnRenamed("label", "before"), "id").where("label < before").count()
        trace.append((graph.name, "hook_compress_classic", k, 1, changed, None, edge_rows, time.perf_counter() - began))
        if not changed:
            break
    return ComponentResult(labels, "hook_compress_classic", k, k, True, trace)


def union_find(graph: Graph, opts: Options, n: int) -> ComponentResult:
    """Forests of the partitions, merged fan_in at a time, then one compressing join. By convention one iteration; the last merge is one task, so the number of ids it may hold is bounded (max_kernel_ids)."""
    began = time.perf_counter()
    kernel = kernels.forest_kernel(opts.max_kernel_ids)
    parts = max(1, n if graph.rows is None else min(n, -(-graph.rows // (kernels.BLOCK_EDGES // 2))))
    forest = (graph.edges if graph.raw is None else graph.raw).repartition(parts).mapInArrow(kernel, "id bigint, label bigint")
    while parts > 1:
        parts = max(1, -(-parts // max(2, opts.fan_in)))
        forest = forest.repartition(parts).mapInArrow(kernel, "id bigint, label bigint")
    labels = stored(graph.vertices.join(forest, "id", "left").select("id", F.coalesce("label", "id").alias("label")))
    return ComponentResult(labels, "union_find", 1, 1, True, [(graph.name, "union_find", 1, 0, None, 0, None, time.perf_counter() - began)])


def bfs(graph: Graph, opts: Options, n: int) -> ComponentResult:
    """Search from all vertices at once: only vertices whose source became smaller send it on."""
    directed, visited = graph.prepared(n), stored(mapping.init_labels(graph.vertices))
    frontier, k, trace = visited, 0, []
    while True:
        _guard(k, opts, "bfs")
        k, began = k + 1, time.perf_counter()
        reached = joined_to(directed, frontier.select(F.col("id").alias("src"), F.col("label").alias("c"))).groupBy(F.col("dst").alias("id")).agg(F.min("c").alias("c"))
        out = stored(visited.join(reached, "id", "left").select("id", F.least("label", F.coalesce("c", "label")).alias("label"), F.col("label").alias("before")))
        frontier, visited = out.where("label < before").select("id", "label"), out.select("id", "label")
        changed = frontier.count()
        trace.append((graph.name, "bfs", k, 1, changed, None, None, time.perf_counter() - began))
        if not changed:
            return ComponentResult(visited, "bfs", k, k, True, trace)


def label_propagation(graph: Graph, opts: Options, n: int) -> ComponentResult:
    """Every vertex takes the least label of itself and its neighbours, until none changes. Its plan shares nothing with min-mapping."""
    edges: DataFrame = graph.own_edges()
    labels, k, trace = stored(graph.vertices.select("id", F.col("id").alias("label"))), 0, []
    while True:
        _guard(k, opts, "label_propagation")
        k, began = k + 1, time.perf_counter()
        forth = edges.join(labels, edges["src"] == labels["id"]).select(F.col("dst").alias("id"), "label")
        back = edges.join(labels, edges["dst"] == labels["id"]).select(F.col("src").alias("id"), "label")
        old = labels
        new = stored(labels.unionByName(forth).unionByName(back).groupBy("id").agg(F.min("label").alias("label")))
        changed = new.join(labels.withColumnRenamed("label", "before"), "id").where("label < before").count()
        labels = new
        discard(old)
        trace.append((graph.name, "label_propagation", k, 1, changed, None, None, time.perf_counter() - began))
        if not changed:
            return ComponentResult(labels, "label_propagation", k, k, True, trace)
