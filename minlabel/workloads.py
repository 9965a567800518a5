"""The experiment graphs, made from the given tables, with what must come out in SQL."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from minlabel import graph as G
from minlabel.ids import dense_ids
from minlabel.session import stored, table


@dataclass
class Workload:
    name: str
    build: Callable[[SparkSession, str], G.Graph]
    edges: str = ""  # SQL: src, dst
    vertices: str = ""  # SQL: id
    closed: str = ""  # SQL: id, label, where a closed form is known
    decoded: str = ""  # name of the key whose vertices (tag 0 of 2) are compared by the smallest key of their component
    low: bool = True  # of low diameter: order-1 methods take few rounds
    stands_for: str = ""

    def oracle(self) -> str:
        body = self.closed or recursive(self.edges, self.vertices)
        if self.decoded:
            return f"with l as ({body}) select id // 2 as {self.decoded}, min(id // 2) over (partition by label) as component from l where id % 2 = 0"
        return f"select cast(id as bigint) as id, cast(label as bigint) as label from ({body})"

    def shown(self, labels: DataFrame, names: DataFrame | None = None) -> DataFrame:
        if names is not None:
            root = names.select(F.col("id").alias("label"), F.col("shown").alias("root"))
            return labels.join(names, "id").join(root, "label").select(F.col("shown").alias("id"), F.col("root").alias("label"))
        if not self.decoded:
            return labels.select("id", "label")
        own = labels.where("id % 2 = 0").select(F.shiftright("id", 1).alias(self.decoded), "label")
        least = own.groupBy("label").agg(F.min(self.decoded).alias("component"))
        return own.join(least, "label").select(self.decoded, "component")


def recursive(edges: str, vertices: str) -> str:
    """Labels by relaxation in DuckDB."""
    more = f" union select id from ({vertices})" if vertices else ""
    return f"""with recursive g as (select distinct src, dst from ({edges}) where src <> dst), e as (select src, dst from g union select dst, src from g),
v as (select src as id from ({edges}) union select dst from ({edges}){more}),
cc(id, label) using key (id) as (select id, id from v union
 (select e.dst, min(cc.label) from cc join e on e.src = cc.id join recurring.cc as r on r.id = e.dst where cc.label < r.label group by e.dst))
select id, label from cc"""


def _ids(spark, d, name, key, tag=0, kinds=2):
    return table(spark, d, name).select(G.tagged(key, tag, kinds).alias("id"))


def order_part(spark, d):
    return G.bipartite_graph(table(spark, d, "lineitem"), "l_orderkey", "l_partkey", _ids(spark, d, "orders", "o_orderkey").union(_ids(spark, d, "part", "p_partkey", 1)), "order_part")


def part_supplier(spark, d):
    return G.bipartite_graph(table(spark, d, "lineitem"), "l_partkey", "l_suppkey", _ids(spark, d, "part", "p_partkey").union(_ids(spark, d, "supplier", "s_suppkey", 1)), "part_supplier")


def customer_order(spark, d):
    return G.bipartite_graph(table(spark, d, "orders"), "o_custkey", "o_orderkey", _ids(spark, d, "customer", "c_custkey"), "customer_order")


def customer_day(spark, d):
    urgent = table(spark, d, "orders").where("o_orderpriority like '1%'").select("o_custkey", F.datediff(F.to_date("o_orderdate"), F.lit("1970-01-01").cast("date")).alias("day"))
    return G.bipartite_graph(urgent, "o_custkey", "day", _ids(spark, d, "customer", "c_custkey"), "customer_day")


def order_part_sparse(spark, d):
    return G.bipartite_graph(table(spark, d, "lineitem").where("l_discount >= 0.10 and l_quantity >= 30"), "l_orderkey", "l_partkey", None, "order_part_sparse")


def fk_hierarchy(spark, d):
    nation, customer, supplier = (table(spark, d, t) for t in ("nation", "customer", "supplier"))
    link = lambda df, a, s, b, t: df.select(G.tagged(a, s, 4).alias("src"), G.tagged(b, t, 4).alias("dst"))
    return G.fk_graph([link(nation, "n_regionkey", 0, "n_nationkey", 1), link(customer, "c_nationkey", 1, "c_custkey", 2), link(supplier, "s_nationkey", 1, "s_suppkey", 3)], "fk_hierarchy")


def event_user_chain(spark, d):
    return G.chain_graph(table(spark, d, "events").select("event_id", "user_id", "ts"), "event_id", ["ts", "event_id"], "user_id", name="event_user_chain")


def event_type_chain(spark, d):
    return G.chain_graph(table(spark, d, "events").select("event_id", "event_type", "ts"), "event_id", ["ts", "event_id"], "event_type", name="event_type_chain")


def event_value_chain(spark, d):
    return G.chain_graph(table(spark, d, "events").select("event_id", "event_type", "value"), "event_id", ["value", "event_id"], "event_type", name="event_value_chain")


def order_date_path(spark, d):
    """One path over all orders. Its order is a range sort with dense places, not a window over everything."""
    keyed = table(spark, d, "orders").select(F.struct("o_orderdate", "o_orderkey").alias("k"))
    placed = stored(dense_ids(keyed, "k").select(F.col("k.o_orderkey").alias("key"), F.col("id").alias("place")))
    after = placed.select(F.col("key").alias("dst"), (F.col("place") - 1).alias("place"))
    return G.Graph.from_edges(placed.withColumnRenamed("key", "src").join(after, "place").select("src", "dst"), None, "order_date_path")


def order_key_path(spark, d):
    keys = table(spark, d, "orders").select(F.col("o_orderkey").alias("src"))
    return G.Graph.from_edges(keys.join(keys.select((F.col("src") - 1).alias("src"), F.col("src").alias("dst")), "src").select("src", "dst"), None, "order_key_path")


SESSION_GAP = "interval 6 hours"


def event_sessions(spark, d):
    return G.chain_graph(table(spark, d, "events").select("event_id", "user_id", "ts"), "event_id", ["ts", "event_id"], "user_id", F.expr(f"next_ts <= ts + {SESSION_GAP}"), name="event_sessions")


def user_prop(spark, d):
    return G.bipartite_graph(table(spark, d, "events").select("user_id", F.get_json_object("props", "$.k").cast("bigint").alias("k")), "user_id", "k", None, "user_prop")


def doc_exact(spark, d):
    return G.equality_graph(table(spark, d, "documents"), "doc_id", F.md5("text"), "doc_exact")


def _keyed(pairs, id, key, name, isolated):
    """id and a text key: the keys by their dense rank."""
    pairs = stored(pairs.dropna().distinct())
    ranks = dense_ids(pairs, key)
    return G.bipartite_graph(pairs.join(ranks, key).select(F.col(id).alias("a"), F.col("id").alias("b")), "a", "b", isolated, name)


def doc_line(spark, d):
    docs = table(spark, d, "documents")
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where("length(line) >= 20")
    return _keyed(lines, "doc_id", "line", "doc_line", docs.select(G.tagged("doc_id", 0).alias("id")))


def page_link(spark, d):
    pages = table(spark, d, "pages")
    links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    return _keyed(links, "page_id", "href", "page_link", pages.select(G.tagged("page_id", 0).alias("id")))


def page_host(spark, d):
    hosts = table(spark, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))
    return _keyed(hosts, "page_id", "host", "page_host", None)


def embedding_sim(spark, d):
    return G.similarity_graph(table(spark, d, "embeddings"), "vec_id", "embedding", 0.35, name="embedding_sim")


def embedding_label(spark, d):
    return G.bipartite_graph(table(spark, d, "embeddings"), "vec_id", "label", None, "embedding_label")


def conversation_chain(spark, d):
    """Each turn with the next of its conversation. Ids are the places of (conv_id, turn), so long conversations do not run into each other; turns are shown as conv_id * 1000 + turn."""
    keyed = table(spark, d, "conversations").where("conv_id is not null and turn is not null").select(F.struct("conv_id", "turn").alias("k"))
    placed = stored(dense_ids(keyed, "k").select("k.conv_id", "k.turn", "id"))
    after = placed.select("conv_id", (F.col("id") - 1).alias("id"), F.col("id").alias("dst"))
    g = G.Graph.from_edges(placed.join(after, ["conv_id", "id"]).select(F.col("id").alias("src"), "dst"), placed.select("id"), "conversation_chain")
    g.names = placed.select("id", (F.col("conv_id").cast("bigint") * 1000 + F.col("turn")).alias("shown"))
    return g


def benchmark_doc(spark, d):
    """Documents that contain a benchmark text: three inner words of the item are looked up among the document's, then the whole is compared. Items of fewer than five words have no inner ones and are compared with each document."""
    docs, items = table(spark, d, "documents"), table(spark, d, "benchmark")
    words = lambda c: F.split(c, r"\s+")
    grams = docs.select("doc_id", words("text").alias("w")).select("doc_id", F.expr("explode(array_distinct(transform(sequence(1, greatest(size(w) - 2, 1)), i -> xxhash64(get(w, i - 1), get(w, i), get(w, i + 1)))))").alias("g"))
    keys = items.withColumn("w", words("text")).where("size(w) >= 5").select("item_id", F.col("text").alias("item"), F.expr("xxhash64(w[1], w[2], w[3])").alias("g"))
    short = items.withColumn("w", words("text")).where("size(w) < 5").select("item_id", F.col("text").alias("item"))
    found = grams.join(F.broadcast(keys) if items.count() <= 100_000 else keys, "g").select("doc_id", "item_id", "item").distinct()
    whole = docs.select("doc_id", "text")
    pairs = found.join(whole, "doc_id").where(F.col("text").contains(F.col("item"))).select("doc_id", "item_id")
    pairs = pairs.unionByName(whole.crossJoin(F.broadcast(short) if short.count() <= 100_000 else short).where(F.col("text").contains(F.col("item"))).select("doc_id", "item_id"))
    return G.bipartite_graph(pairs, "doc_id", "item_id", _ids(spark, d, "documents", "doc_id").union(_ids(spark, d, "benchmark", "item_id", 1)), "benchmark_doc")


def permuted(c, k: int):
    """A bijection of 0..2**k-1: odd factors and shifted xors."""
    mask = (1 << k) - 1
    x = c.cast("bigint")
    for m, s in ((0x9E3779B1, (k + 1) // 2), (0x85EBCA77, (k + 2) // 3), (0xC2B2AE3D, (k + 1) // 2)):
        x = (x * F.lit(m | 1)).bitwiseAND(F.lit(mask))
        x = x.bitwiseXOR(F.shiftright(x, s))
    return x


def lattice(spark: SparkSession, k: int, permute: bool = False) -> G.Graph:
    """Triangulated grid of 2**k points: neighbours to the right, below, and below right."""
    w = 1 << (k // 2)
    points = spark.range(1 << k)
    near = F.array(F.when((F.col("id") + 1) % w != 0, F.col("id") + 1), F.when(F.col("id") + w < (1 << k), F.col("id") + w), F.when(((F.col("id") + 1) % w != 0) & (F.col("id") + w < (1 << k)), F.col("id") + w + 1))
    edges = points.select(F.col("id").alias("src"), F.explode(near).alias("dst")).where("dst is not null")
    if permute:
        edges = edges.select(permuted(F.col("src"), k).alias("src"), permuted(F.col("dst"), k).alias("dst"))
    return G.Graph.from_edges(edges, points, f"lattice{k}{'p' if permute else ''}")


def part_lattice(spark, d, name: str, permute: bool = False) -> G.Graph:
    """Triangulated grid of the parts, row by row in the order of their keys, or of hashes of these; as lattice(), its last row may be shorter."""
    keys = table(spark, d, "part").where("p_partkey is not null").select(F.struct(F.xxhash64("p_partkey").alias("h") if permute else F.lit(0).alias("h"), F.col("p_partkey").cast("bigint").alias("key")).alias("k"))
    placed = stored(dense_ids(keys, "k").select("k.key", F.col("id").alias("place")), "places")
    n = placed.count()
    w, inner = max(1, math.isqrt(n)), (F.col("place") + 1) % max(1, math.isqrt(n)) != 0
    near = F.array(F.when(inner, F.col("place") + 1), F.col("place") + w, F.when(inner, F.col("place") + w + 1))
    ends = placed.select(F.col("key").alias("src"), F.explode(near).alias("place")).where("place is not null")
    return G.Graph.from_edges(ends.join(placed.withColumnRenamed("key", "dst"), "place").select("src", "dst"), placed.select(F.col("key").alias("id")), name)


def generate(spark: SparkSession, kind: str, n: int, seed: int = 0, factor: float = 1.0) -> G.Graph:
    """path, cycle, star, clique, random or forest on 0..n-1, from a range and expressions only."""
    v = spark.range(n)
    if kind == "path":
        e = spark.range(max(n - 1, 0)).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    elif kind == "cycle":
        e = v.select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst"))
    elif kind == "star":
        e = v.where("id > 0").select(F.lit(0).cast("bigint").alias("src"), F.col("id").alias("dst"))
    elif kind == "clique":
        e = v.where("id > 0").select(F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("id") - 1)).alias("src"), F.col("id").alias("dst"))
    elif kind == "random":
        h = lambda s: F.pmod(F.xxhash64(F.col("id"), F.lit(seed), F.lit(s)), F.lit(n))
        e = spark.range(int(n * factor)).select(h("a").alias("src"), h("b").alias("dst"))
    elif kind == "forest":
        e = v.where("id % 7 > 0").select(F.pmod(F.xxhash64("id", F.lit(seed)), F.col("id")).alias("src"), F.col("id").alias("dst"))
    else:
        raise ValueError(f"no kind {kind}")
    return G.Graph.from_edges(e, v, kind)


_tag = "select {0} * 2 as id from {1}"
_lines = "select distinct doc_id, l from (select doc_id, unnest(string_split(text, chr(10))) as l from documents) where length(l) >= 20"
_links = "select distinct page_id, l from (select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as l from pages)"
_hosts = "select page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as l from pages"
_ranked = lambda id, q: f"select {id} * 2 as src, (dense_rank() over (order by l)) * 2 + 1 as dst from ({q})"
_least = lambda by, t: f"select event_id as id, min(event_id) over (partition by {by}) as label from {t}"
_dot = "list_sum(list_transform(range(1, 65), lambda i: cast({0}[i] as double) * cast({1}[i] as double)))"
WORKLOADS = {w.name: w for w in (
    Workload("order_part", order_part, "select l_orderkey * 2 as src, l_partkey * 2 + 1 as dst from lineitem", "select o_orderkey * 2 as id from orders union select p_partkey * 2 + 1 from part", stands_for="social graph, one giant component"),
    Workload("part_supplier", part_supplier, "select l_partkey * 2 as src, l_suppkey * 2 + 1 as dst from lineitem", "select p_partkey * 2 as id from part union select s_suppkey * 2 + 1 from supplier", stands_for="heavy hubs"),
    Workload("customer_order", customer_order, "select o_custkey * 2 as src, o_orderkey * 2 + 1 as dst from orders", "select c_custkey * 2 as id from customer", stands_for="many small stars"),
    Workload("customer_day", customer_day, "select o_custkey * 2 as src, datediff('day', date '1970-01-01', cast(o_orderdate as date)) * 2 + 1 as dst from orders where o_orderpriority like '1%'", "select c_custkey * 2 as id from customer", stands_for="sparse random graph near percolation"),
    Workload("order_part_sparse", order_part_sparse, "select l_orderkey * 2 as src, l_partkey * 2 + 1 as dst from lineitem where l_discount >= 0.10 and l_quantity >= 30", stands_for="many small components"),
    Workload("fk_hierarchy", fk_hierarchy, "select n_regionkey * 4 as src, n_nationkey * 4 + 1 as dst from nation union all select c_nationkey * 4 + 1, c_custkey * 4 + 2 from customer union all select s_nationkey * 4 + 1, s_suppkey * 4 + 3 from supplier", stands_for="shallow trees"),
    Workload("event_user_chain", event_user_chain, closed=_least("user_id", "events"), low=False, stands_for="sequences with increasing ids"),
    Workload("event_type_chain", event_type_chain, closed=_least("event_type", "events"), low=False, stands_for="very long path, increasing ids"),
    Workload("event_value_chain", event_value_chain, closed=_least("event_type", "events"), low=False, stands_for="long path with shuffled ids"),
    Workload("order_date_path", order_date_path, closed="select o_orderkey as id, min(o_orderkey) over () as label from orders", low=False, stands_for="road-like path, shuffled ids"),
    Workload("order_key_path", order_key_path, closed="select o_orderkey as id, min(o_orderkey) over (partition by o_orderkey - n) as label from (select o_orderkey, row_number() over (order by o_orderkey) as n from orders)", low=False, stands_for="sorted path"),
    Workload("event_sessions", event_sessions, closed=f"select event_id as id, min(event_id) over (partition by user_id, n) as label from (select *, sum(f) over (partition by user_id order by ts, event_id) as n from (select event_id, user_id, ts, case when ts <= lag(ts) over (partition by user_id order by ts, event_id) + {SESSION_GAP.replace('6 hours', chr(39) + '6 hours' + chr(39))} then 0 else 1 end as f from events))", stands_for="short chains"),
    Workload("user_prop", user_prop, "select user_id * 2 as src, cast(json_extract_string(props, '$.k') as bigint) * 2 + 1 as dst from events", stands_for="small dense bipartite graph"),
    Workload("doc_exact", doc_exact, closed="select doc_id as id, min(doc_id) over (partition by md5(text)) as label from documents", stands_for="duplicate clusters"),
    Workload("doc_line", doc_line, _ranked("doc_id", _lines), _tag.format("doc_id", "documents"), decoded="doc_id", stands_for="web-like skew and many components"),
    Workload("page_link", page_link, _ranked("page_id", _links), _tag.format("page_id", "pages"), decoded="page_id", stands_for="web graph"),
    Workload("page_host", page_host, _ranked("page_id", _hosts), decoded="page_id", stands_for="stars"),
    Workload("embedding_sim", embedding_sim, f"select a.vec_id as src, b.vec_id as dst from (select vec_id, embedding as e, sqrt({_dot.format('embedding', 'embedding')}) as n from embeddings) a join (select vec_id, embedding as e, sqrt({_dot.format('embedding', 'embedding')}) as n from embeddings) b on a.vec_id < b.vec_id where {_dot.format('a.e', 'b.e')} > 0.35 * a.n * b.n", "select vec_id as id from embeddings", stands_for="similarity graph"),
    Workload("embedding_label", embedding_label, "select vec_id * 2 as src, label * 2 + 1 as dst from embeddings", stands_for="stars"),
    Workload("conversation_chain", conversation_chain, closed="select conv_id * 1000 + turn as id, min(conv_id * 1000 + turn) over (partition by conv_id) as label from conversations", stands_for="short chains"),
    Workload("benchmark_doc", benchmark_doc, "select doc_id * 2 as src, item_id * 2 + 1 as dst from documents d join benchmark b on contains(d.text, b.text)", "select doc_id * 2 as id from documents union select item_id * 2 + 1 from benchmark", stands_for="sparse contamination graph"),
    Workload("lattice12", lambda spark, d: part_lattice(spark, d, "lattice12"), closed="select p_partkey as id, min(p_partkey) over () as label from part", low=False, stands_for="triangulation family"),
    Workload("lattice12p", lambda spark, d: part_lattice(spark, d, "lattice12p", True), closed="select p_partkey as id, min(p_partkey) over () as label from part", low=False, stands_for="triangulation family, shuffled ids"),
)}


def graph_catalog(spark: SparkSession, sf_dir: str, names: list[str] | None = None, built: Callable[[SparkSession, str, str], G.Graph] | None = None) -> DataFrame:
    """Name, number, edges and vertices (with an edge) of the experiment graphs; built: where they are had from, if they are made already."""
    out = None
    for k, name in enumerate(names or WORKLOADS):
        g = built(spark, sf_dir, name) if built else WORKLOADS[name].build(spark, sf_dir)
        edges = g.own_edges()
        ends = edges.select(F.explode(F.array("src", "dst")).alias("id"))
        both = edges.groupBy().agg(F.count("*").alias("edges")), ends.agg(F.countDistinct("id").alias("vertices"))
        row = both[0].withColumn("one", F.lit(1)).join(both[1].withColumn("one", F.lit(1)), "one").select(F.lit(name).alias("graph"), F.lit(k + 1).alias("number"), "edges", "vertices")
        out = row if out is None else out.unionByName(row)
    return out
