"""The registered queries of the library and their oracles."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from minlabel import relational, reports
from minlabel.operators import mapping
from minlabel.plans import experiments, measures
from minlabel.plans.engine import connected_components
from minlabel.workloads import WORKLOADS, graph_catalog

EVERY = ("sync2", "order1", "order2", "orderm", "low_then_high", "alternate", "block_async", "chained", "hook_compress", "hook_compress_classic", "union_find", "bfs", "label_propagation")
ON_ALL = ("order2", "orderm", "union_find")
FULL = ("customer_order", "order_part_sparse", "doc_exact", "page_host", "conversation_chain")
SPARSE = "order_part_sparse"
VARIANTS = {
    "retired": {"retire": True}, "contracted": {"contract_after": 1}, "fused": {"early_check": "fused"}, "synchronous": {"update": "sync"},
    "in_small_blocks": {"block_edges": 300}, "one_sweep": {"local_sweeps": 1, "block_edges": 300},
}
#: Graphs whose edges have SQL.
LISTED = [w.name for w in WORKLOADS.values() if w.edges]


def components(spark: SparkSession, sf_dir: str, graph: str, method: str, **options) -> DataFrame:
    w = WORKLOADS[graph]
    g = w.build(spark, sf_dir)
    return w.shown(connected_components(g, method, **options).labels, g.names)


def state(spark: SparkSession, sf_dir: str, order: int, rounds: int) -> DataFrame:
    """Labels of the sparse graph after some synchronous rounds."""
    from minlabel.session import stored

    g = WORKLOADS[SPARSE].build(spark, sf_dir)
    labels = mapping.init_labels(g.vertices)
    for _ in range(rounds):
        labels = stored(mapping.apply_min_mapping(g.edges, labels, order))
    return labels


def _states() -> dict[str, Callable]:
    first = lambda f: lambda spark, d: f(state(spark, d, 2, 1))

    def neighbours(spark, d):
        return mapping.root_neighbours(state(spark, d, 2, 1), WORKLOADS[SPARSE].build(spark, d).edges)

    return {f"minmap_o{h}_k{k}": (lambda spark, d, h=h, k=k: state(spark, d, h, k)) for h in (1, 2) for k in (1, 2)} | {
        "ems1_k1": first(lambda x: mapping.equal_minimum_sets(x, 1)),
        "ems2_k1": first(lambda x: mapping.equal_minimum_sets(x, 2)),
        "mms1_k1": first(lambda x: mapping.merged_minimum_set(x, 1)),
        "mms2_k1": first(lambda x: mapping.merged_minimum_set(x, 2)),
        "roots_k1": first(mapping.roots),
        "root_neighbours_k1": neighbours,
        "pointer_square": first(lambda x: mapping.power_labels(x, 2)),
        "tree_heights_k1": first(mapping.tree_heights),
    }


def _state_sql(order: int, rounds: int, tail: str) -> str:
    """Rounds spelled out from the operator's definition: for each edge the smaller of the labels order hops away goes to both ends and their chains."""
    w = WORKLOADS[SPARSE]
    parts = [f"e as (select distinct src, dst from ({w.edges}))", "l0 as (select distinct id, id as label from (select src as id from e union all select dst from e))"]
    for k in range(1, rounds + 1):
        p = f"l{k - 1}"
        if order == 1:
            parts.append(f"z{k} as (select src as a, dst as b, least(x.label, y.label) as z from e join {p} x on src = x.id join {p} y on dst = y.id)")
            targets = f"select a as id, z from z{k} union all select b, z from z{k}"
        else:
            parts.append(f"z{k} as (select src as a, dst as b, x.label as la, y.label as lb, least(xx.label, yy.label) as z from e join {p} x on src = x.id join {p} y on dst = y.id join {p} xx on x.label = xx.id join {p} yy on y.label = yy.id)")
            targets = " union all ".join(f"select {c} as id, z from z{k}" for c in ("a", "b", "la", "lb"))
        parts.append(f"l{k} as (select l.id, least(l.label, coalesce(min(t.z), l.label)) as label from {p} l left join ({targets}) t on l.id = t.id group by l.id, l.label)")
    return f"with {', '.join(parts)} {tail}"


def _reports() -> dict[str, tuple[Callable, str | None]]:
    small, big = WORKLOADS[SPARSE], WORKLOADS["customer_order"]
    labels = lambda spark, d, w=small: connected_components(w.build(spark, d), "order2").labels

    def checked(w):
        return lambda spark, d: (lambda g: measures.violations(g, connected_components(g, "order2").labels))(w.build(spark, d))

    def isolated(spark, d):
        g = big.build(spark, d)
        ends = g.edges.select(F.explode(F.array("src", "dst")).alias("id"))
        return connected_components(g, "order2").labels.join(ends, "id", "left_anti")

    def differing(spark, d):
        g = small.build(spark, d)
        a, b = connected_components(g, "order1").labels, connected_components(g, "orderm").labels.withColumnRenamed("label", "other")
        return a.join(b, "id", "full").agg(F.count_if(~F.col("label").eqNullSafe(F.col("other"))).alias("different"))

    def sales(spark, d):
        from minlabel.session import table

        parts = connected_components(big.build(spark, d), "order2").labels.where("id % 2 = 1").select(F.shiftright("id", 1).alias("o_orderkey"), "label")
        return table(spark, d, "orders").join(parts, "o_orderkey").groupBy("label").agg(F.count("*").alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total"))

    def subgraph(spark, d):
        from minlabel.graph import subgraph as cut

        return connected_components(cut(big.build(spark, d), F.col("id") % 3 > 0), "order2").labels

    zero = "select 0 as crossing_edges, 0 as larger_labels, 0 as labels_not_roots"
    kept = "select src, dst from ({}) where src % 3 > 0 and dst % 3 > 0"
    from minlabel.workloads import recursive

    out = {
        "component_sizes_sparse": (lambda s, d: measures.component_sizes(labels(s, d)), f"select label as component, count(*) as size, min(id) as min_id, max(id) as max_id from ({small.oracle()}) group by 1"),
        "component_histogram": (lambda s, d: measures.component_histogram(labels(s, d)), f"select size, count(*) as components from (select count(*) as size from ({small.oracle()}) group by label) group by 1"),
        "topk_components": (lambda s, d: measures.component_sizes(labels(s, d)).orderBy(F.desc("size"), "component").limit(10), f"select label as component, count(*) as size, min(id) as min_id, max(id) as max_id from ({small.oracle()}) group by 1 order by 2 desc, 1 limit 10"),
        "component_representative": (lambda s, d: labels(s, d).groupBy("label").agg(F.max_by("id", "id").alias("last_id")), f"select label, max(id) as last_id from ({small.oracle()}) group by 1"),
        "degree_histogram": (lambda s, d: measures.degree_histogram(WORKLOADS["part_supplier"].build(s, d).edges), f"select degree, count(*) as vertices from (select id, count(*) as degree from (select src as id from (select distinct src, dst from ({WORKLOADS['part_supplier'].edges})) union all select dst from (select distinct src, dst from ({WORKLOADS['part_supplier'].edges}))) group by id) group by 1"),
        "isolated_customers_keep_label": (isolated, "select c_custkey * 2 as id, c_custkey * 2 as label from customer where c_custkey not in (select o_custkey from orders)"),
        "labelings_diff": (differing, "select 0 as different"),
        "sales_by_component": (sales, "select least(o_custkey * 2, min(o_orderkey) * 2 + 1) as label, count(*) as orders, round(sum(o_totalprice), 2) as total from orders group by o_custkey"),
        "subgraph_components": (subgraph, f"select cast(id as bigint) as id, cast(label as bigint) as label from ({recursive(kept.format(big.edges), f'select id from (select src as id from ({big.edges}) union select dst from ({big.edges}) union {big.vertices}) where id % 3 > 0')})"),
        "min_neighbour_label": (lambda s, d: (lambda g: mapping.neighbour_minimum(g.prepared(4), mapping.init_labels(g.vertices), "label"))(small.build(s, d)), f"select id, min(n) as label from (select src as id, dst as n from ({small.edges}) union all select dst, src from ({small.edges})) group by id"),
        "graph_catalog": (lambda s, d: graph_catalog(s, d, LISTED), " union all ".join(f"select '{w.name}' as graph, {k} as number, (select count(*) from (select distinct src, dst from ({w.edges}))) as edges, (select count(*) from (select src from ({w.edges}) union select dst from ({w.edges}))) as vertices" for k, w in enumerate((WORKLOADS[x] for x in LISTED), 1))),
        "experiment_iterations": (lambda s, d: measures.iterations(experiments.traces(s, d, reports.MEASURED)).select("graph", "method", "iterations"), None),
        "experiment_order_relation": (lambda s, d: measures.order_relation(experiments.traces(s, d, reports.MEASURED, ("orderm", "order2", "order1"))), f"select graph, true as holds from (values {', '.join(f'({n!r})' for n in reports.MEASURED)}) t(graph)"),
        "experiment_speedup_hook_compress": (lambda s, d: experiments.speedups(s, d, reports.MEASURED), None),
        "experiment_speedup_union_find": (lambda s, d: experiments.speedups(s, d, reports.MEASURED, "union_find"), None),
        "experiment_growth": (lambda s, d: experiments.growth(s, range(10, 15, 4), methods=("order2", "orderm", "union_find", "hook_compress")), None),
        "experiment_cores": (lambda s, d: experiments.core_times(s, SPARSE, d, (1, 4)), None),
        "experiment_ablation": (lambda s, d: experiments.ablation(s, d, [SPARSE, "customer_day"]), None),
        "experiment_communication": (lambda s, d: experiments.communication(s, d, reports.SHALLOW), None),
    }
    for name in (SPARSE, "customer_day"):
        out[f"validate_{name}"] = (checked(WORKLOADS[name]), zero)
    return out


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return components(spark, sf_dir, "order_part", "order2")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    out: dict[str, Callable] = {}
    for name in WORKLOADS:
        for m in EVERY if name in FULL else ON_ALL:
            out[f"cc_{m}_{name}"] = partial(components, graph=name, method=m)
    out |= {f"cc_{k}_{SPARSE}": partial(components, graph=SPARSE, method="order2", **o) for k, o in VARIANTS.items()}
    out[f"cc_schedule_{SPARSE}"] = partial(components, graph=SPARSE, method="schedule", orders=[1, 3, 2])
    return out | _states() | {k: f for k, (f, _) in _reports().items()} | relational.QUERIES | reports.QUERIES


def oracle_sql() -> dict[str, str]:
    out = {k: WORKLOADS[k.split("_", 1)[1].removeprefix(next(m for m in (*EVERY, *VARIANTS, "schedule") if k.startswith(f"cc_{m}_") and k[len(m) + 4 :] in WORKLOADS) + "_")].oracle() for k in queries() if k.startswith("cc_")}
    shown = "select cast(id as bigint) as id, cast(label as bigint) as label from l{}"
    out |= {f"minmap_o{h}_k{k}": _state_sql(h, k, shown.format(k)) for h in (1, 2) for k in (1, 2)}
    square = "(select a.id, b.label from l1 a join l1 b on a.label = b.id)"
    final = "with recursive u as (select id, id as label, 0 as hops from l1 union all select u.id, l1.label, hops + 1 from u join l1 on u.label = l1.id where l1.label < l1.id) select id, label, hops from u where label in (select id from l1 where id = label)"
    out |= {
        "ems1_k1": _state_sql(2, 1, "select label, count(*) as size from l1 group by 1"),
        "ems2_k1": _state_sql(2, 1, f"select label, count(*) as size from {square} group by 1"),
        "mms1_k1": _state_sql(2, 1, "select distinct label from l1"),
        "mms2_k1": _state_sql(2, 1, f"select distinct label from {square}"),
        "roots_k1": _state_sql(2, 1, "select id from l1 where id = label"),
        "pointer_square": _state_sql(2, 1, f"select id, label from {square}"),
        "root_neighbours_k1": _state_sql(2, 1, f"select distinct least(x.label, y.label) as root_a, greatest(x.label, y.label) as root_b from e join ({final}) x on src = x.id join ({final}) y on dst = y.id where x.label <> y.label"),
        "tree_heights_k1": _state_sql(2, 1, f"select label as root, max(hops) as height from ({final}) group by label"),
    }
    return out | {k: q for k, (_, q) in _reports().items() if q} | relational.ORACLES | reports.ORACLES
