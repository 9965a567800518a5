"""Measures of methods and results, forest observers, and what SQL users see, each a query with its SQL where there is one."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from minlabel import relational
from minlabel.functions.sql import register_result, register_sql
from minlabel.graph import Graph, chain_graph
from minlabel.operators import mapping
from minlabel.plans import advisor, experiments, measures
from minlabel.plans.engine import connected_components
from minlabel.session import stored, table
from minlabel.workloads import WORKLOADS, generate, graph_catalog

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
query = relational.registrar(QUERIES, ORACLES)

SPARSE, BIG = WORKLOADS["order_part_sparse"], WORKLOADS["customer_order"]
SHALLOW = ("order_part_sparse", "customer_day", "fk_hierarchy")
#: Graphs of the measures of methods: shallow ones, chains, a dense one, and a lattice with shuffled ids.
MEASURED = (*SHALLOW, "user_prop", "conversation_chain", "event_user_chain", "event_value_chain", "lattice12p")
BOUNDED = ("order2", "orderm", "low_then_high", "alternate", "sync2")


def _labels(spark: SparkSession, d: str, w) -> DataFrame:
    return connected_components(w.build(spark, d), "order2").labels


def _ends(edges: str) -> str:
    return f"select src as id, dst as other from (select distinct src, dst from ({edges})) union all select dst, src from (select distinct src, dst from ({edges}))"


def _all_true(names, columns: str = "graph") -> str:
    return f"select {columns}, true as holds from (values {', '.join(map(str, names))}) t({columns})"


# Joins and aggregates of edges with their labels.


@query(f"select label, count(*) as edges from (select distinct src, dst from ({BIG.edges})) e join ({BIG.oracle()}) l on e.src = l.id group by label")
def join_edges_labels(spark, d):
    g = BIG.build(spark, d)
    return g.edges.join(connected_components(g, "order2").labels, F.col("src") == F.col("id")).groupBy("label").agg(F.count("*").alias("edges"))


@query(f"""select label, o_orderstatus, count(*) as orders, round(sum(o_totalprice), 2) as total from orders join ({BIG.oracle()}) l on l.id = o_orderkey * 2 + 1
group by grouping sets ((label, o_orderstatus), (label), ())""")
def rollup_component_sales(spark, d):
    own = _labels(spark, d, BIG).where("id % 2 = 1").select(F.shiftright("id", 1).alias("o_orderkey"), "label")
    return table(spark, d, "orders").join(own, "o_orderkey").rollup("label", "o_orderstatus").agg(F.count("*").alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total"))


def _links(name: str, key: str):
    def run(spark, d):
        ends = WORKLOADS[name].build(spark, d).edges.select(F.explode(F.array("src", "dst")).alias("id"))
        return ends.where("id % 2 = 0").groupBy(F.shiftright("id", 1).alias(key)).agg(F.count("*").alias("links"))

    return run


for _query, _name, _key in (("doc_line_edges", "doc_line", "doc_id"), ("page_links", "page_link", "page_id"), ("page_hosts", "page_host", "page_id")):
    QUERIES[_query] = _links(_name, _key)
    ORACLES[_query] = f"select id // 2 as {_key}, count(*) as links from ({_ends(WORKLOADS[_name].edges)}) where id % 2 = 0 group by 1"


@query(f"select count(distinct label) as components, count(*) as vertices from ({SPARSE.oracle()})")
def sql_surface_components(spark, d):
    register_result(_labels(spark, d, SPARSE), "surface")
    return spark.sql("select count(*) as components, sum(size) as vertices from surface_sizes")


@query("select p_partkey as d, case when p_partkey > 1 then cast(ceil(ln(p_partkey) / ln(1.5)) as bigint) + 1 else 2 end as bound from part")
def sql_surface_bound(spark, d):
    register_sql(spark)
    return table(spark, d, "part").select(F.col("p_partkey").cast("bigint").alias("d"), F.expr("min_map_bound(p_partkey)").alias("bound"))


# Observers of the forest.


@query("select cast(n as integer) as points, n - 1 - greatest(0, n - 1 - k) as settled, k as round from range(1, 6) t(k), (select count(*) as n from customer)")
def order1_spreads_one_hop(spark, d):
    """On a path, of the customers in the order of their keys, each round of order 1 carries the smallest label one edge further."""
    g, rows = chain_graph(table(spark, d, "customer"), "c_custkey", ["c_custkey"]), []
    edges, labels = g.own_edges(), stored(mapping.init_labels(g.vertices))
    points, least = labels.agg(F.count("*"), F.min("id")).first()
    for k in range(1, 6):
        labels = stored(mapping.apply_min_mapping(edges, labels, 1))
        rows.append((points, labels.where(F.col("label") == least).count() - 1, k))
    return spark.createDataFrame(rows, "points int, settled bigint, round bigint")


@query(_all_true([f"('{n}')" for n in SHALLOW]))
def merged_minimum_chain(spark, d):
    """Labels in use after a round are among those in use before it."""
    rows = []
    for name in SHALLOW:
        g = WORKLOADS[name].build(spark, d)
        labels, states = mapping.init_labels(g.vertices), []
        for _ in range(3):
            labels = stored(mapping.apply_min_mapping(g.edges, labels, 2))
            states.append(labels)
        rows.append((name, mapping.mms_chain_holds(states)))
    return spark.createDataFrame(rows, "graph string, holds boolean")


@query(_all_true([f"({h})" for h in (2, 3, 4, 8)], "step_order"))
def tree_heights_shrink(spark, d):
    """One step of order h leaves at most a h-th, rounded up, of a tree's height."""
    rows, height = [], 23
    chain = stored(spark.range(height + 1).select("id", F.greatest(F.col("id") - 1, F.lit(0)).alias("label")))
    edges = chain.where("label < id").select(F.col("label").alias("src"), F.col("id").alias("dst"))
    for h in (2, 3, 4, 8):
        after = mapping.tree_heights(stored(mapping.apply_min_mapping(edges, chain, h))).agg(F.max("height")).first()[0]
        rows.append((h, after <= mapping.height_after(height, h)))
    return spark.createDataFrame(rows, "step_order int, holds boolean")


@query("select 'path64' as graph, applications, true as holds from (values (1), (2)) t(applications)")
def root_tree_constraint(spark, d):
    """1.5 to the power of the finished rounds, times the sum of heights, stays under the number of vertices of a path."""
    g, rows = generate(spark, "path", 64), []
    for applications in (1, 2):
        rows.append(("path64", applications, all(1.5 ** (k - 1) * total <= 63 for k, total in measures.root_tree_sums(g, applications=applications))))
    return spark.createDataFrame(rows, "graph string, applications int, holds boolean")


# Measures of the methods over several graphs.


def _trace(spark, d, graphs=MEASURED, methods=experiments.COMPARED) -> DataFrame:
    return experiments.traces(spark, d, graphs, methods)


RELATIONS = (("orderm", "order2"), ("order2", "order1"), ("order2", "sync2"), ("sync2", "hook_compress"), ("low_then_high", "hook_compress"), ("alternate", "hook_compress"), ("union_find", "orderm"))


def _related(graph: str):
    """Which method takes at most as many rounds as which, on one graph."""

    def run(spark, d):
        by = {m: len(experiments.rounds_of(spark, d, graph, m)) for m in experiments.COMPARED if experiments.runs(graph, m)}
        rows = [(graph, a, b, by[a] <= by[b]) for a, b in RELATIONS if a in by and b in by]
        return spark.createDataFrame(rows, "graph string, method string, other string, holds boolean")

    return run


for _graph in MEASURED:
    QUERIES[f"experiment_iterations_{_graph}"] = _related(_graph)
    ORACLES[f"experiment_iterations_{_graph}"] = _all_true([f"('{_graph}', '{a}', '{b}')" for a, b in RELATIONS if experiments.runs(_graph, a) and experiments.runs(_graph, b)], "graph, method, other")


@query(_all_true([f"('{n}', '{m}')" for n in SHALLOW for m in BOUNDED], "graph, method"))
def iteration_bound_holds(spark, d):
    """Rounds that lowered a label against the bound that follows from the diameter found by two sweeps."""
    most = {n: measures.iteration_bound(measures.diameter(WORKLOADS[n].build(spark, d))) for n in SHALLOW}
    bound = spark.createDataFrame(list(most.items()), "graph string, bound int")
    rounds = _trace(spark, d, SHALLOW, BOUNDED).groupBy("graph", "method").agg(F.count_if(F.col("changed") > 0).alias("iterations"))
    return rounds.join(bound, "graph").select("graph", "method", (F.col("iterations") <= F.col("bound")).alias("holds"))


@query()
def mean_iterations(spark, d):
    return measures.mean_iterations(_trace(spark, d))


@query()
def compared_iterations(spark, d):
    return measures.compare_iterations(_trace(spark, d, methods=("low_then_high", "alternate")), "low_then_high", "alternate")


@query()
def saved_iterations(spark, d):
    return measures.compare_iterations(_trace(spark, d, methods=("orderm", "order2")), "orderm", "order2")


@query()
def trace_deltas(spark, d):
    return measures.trace_deltas(_trace(spark, d, methods=("order2", "sync2"))).select("graph", "method", "iteration", "changed", "before")


@query(_all_true([f"('{n}', 'sync2')" for n in MEASURED], "graph, method"))
def hooking_rounds_match(spark, d):
    """The synchronous variant takes at most as many rounds as hooking and compressing."""
    by = measures.iterations(_trace(spark, d, methods=("sync2", "hook_compress"))).groupBy("graph").pivot("method", ["sync2", "hook_compress"]).agg(F.max("iterations"))
    return by.select("graph", F.lit("sync2").alias("method"), (F.col("sync2") <= F.col("hook_compress")).alias("holds"))


@query()
def work_depth(spark, d):
    """Edges for each of 64 cores, times rounds."""
    sizes = graph_catalog(spark, d, list(MEASURED), experiments.built).select("graph", "edges")
    return measures.iterations(_trace(spark, d)).join(sizes, "graph").select("graph", "method", (F.col("edges") / 64 * F.col("iterations")).alias("work"))


@query()
def recommended_methods(spark, d):
    rows = []
    for name in SHALLOW:
        stats, finished = advisor.sampled_stats(WORKLOADS[name].build(spark, d))
        for cores in (8, 1024):
            r = advisor.recommend_method(stats, cores, finished)
            rows.append((name, cores, stats["diameter_lb"], finished, r.method, r.reason))
    return spark.createDataFrame(rows, "graph string, cores int, diameter_lb int, finished_share double, method string, reason string")


@query("select 7 as hops, 'path8' as graph union all select 4, 'cycle8' union all select 2, 'star9' union all select 1, 'clique5'")
def exact_diameters(spark, d):
    """Of graphs whose diameters are known."""
    out = None
    for kind, n in (("path", 8), ("cycle", 8), ("star", 9), ("clique", 5)):
        g = generate(spark, kind, n)
        row = measures.exact_diameters(g, connected_components(g).labels).agg(F.max("diameter").alias("hops")).withColumn("graph", F.lit(f"{kind}{n}"))
        out = row if out is None else out.unionByName(row)
    return out


@query(f"select label as component, cast(case when count(*) > 2 then 2 else count(*) - 1 end as integer) as diameter from ({BIG.oracle()}) group by label")
def component_diameters(spark, d):
    """Of stars: one hop for a pair, two for more."""
    g = BIG.build(spark, d)
    return measures.diameters(g, connected_components(g, "order2").labels)


def _degrees(name: str) -> str:
    return f"select '{name}' as graph, count(*) as n, max(degree) as max_degree, round(avg(degree), 9) as mean_degree from (select id, count(*) as degree from ({_ends(WORKLOADS[name].edges)}) group by id)"


@query(" union all ".join(map(_degrees, (*SHALLOW, "order_part", "part_supplier"))))
def degree_profiles(spark, d):
    """Even or steep: the largest degree against the mean."""
    out = None
    for name in (*SHALLOW, "order_part", "part_supplier"):
        row = measures.degrees(WORKLOADS[name].build(spark, d).edges).agg(F.count("*").alias("n"), F.max("degree").alias("max_degree"), F.round(F.avg("degree"), 9).alias("mean_degree")).select(F.lit(name).alias("graph"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query(f"select count(*) as vertices, count(distinct label) as components, count(*) - count(distinct label) as forest_edges from ({SPARSE.oracle()})")
def forest_rank(spark, d):
    """A spanning forest has as many edges as there are vertices less components: counted once from labels, once from a union-find forest."""
    g: Graph = SPARSE.build(spark, d)
    counted = connected_components(g, "order2").labels.agg(F.count("*").alias("vertices"), F.countDistinct("label").alias("components"))
    forest = connected_components(g, "union_find").labels.where("label < id").agg(F.count("*").alias("forest_edges"))
    return counted.withColumn("k", F.lit(1)).join(forest.withColumn("k", F.lit(1)), "k").drop("k")
