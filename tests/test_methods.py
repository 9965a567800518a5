import random

import pytest

from minlabel.graph import Graph, similarity_graph
from minlabel.operators import mapping
from minlabel.plans import measures
from minlabel.plans.engine import METHODS, NotConverged, connected_components
from minlabel.workloads import WORKLOADS, generate
from tests.conftest import SMOKE
from tests.helpers import rows, union_find


def made(spark, edges, n, name="t"):
    return Graph.from_edges(spark.createDataFrame(edges, "src bigint, dst bigint"), spark.range(n), name)


def labels(result):
    return {r.id: r.label for r in result.labels.collect()}


def chains(labels_, v, h):
    out = [v]
    for _ in range(h - 1):
        out.append(labels_[out[-1]])
    return out


def literal_round(labels_, edges, h):
    """The operator spelled out edge by edge."""
    new = dict(labels_)
    for a, b in edges:
        ca, cb = chains(labels_, a, h), chains(labels_, b, h)
        z = min(labels_[ca[-1]], labels_[cb[-1]])
        for v in ca + cb:
            new[v] = min(new[v], z)
    return new


GRAPHS = {
    "partial": (5, [(2, 4), (4, 3), (2, 1), (3, 0)]),
    "loops": (4, [(1, 1), (0, 1), (1, 0), (0, 1)]),
    "mixed": (30, [(random.Random(4).randrange(30), i) for i in range(9)] + [(i, (i * 7) % 30) for i in range(12, 24)]),
}


@pytest.mark.parametrize("method", [m for m in METHODS if m != "schedule"])
def test_methods_agree(spark, method):
    for name, (n, edges) in GRAPHS.items():
        assert labels(connected_components(made(spark, edges, n), method)) == union_find(range(n), edges), name


@pytest.mark.parametrize("options", [{"retire": True}, {"contract_after": 1}, {"early_check": "fused"}, {"early_check": "off"}, {"applications": 2}])
def test_options(spark, options):
    n, edges = GRAPHS["partial"]
    assert labels(connected_components(made(spark, edges, n), "order2", **options)) == union_find(range(n), edges)


@pytest.mark.parametrize("h", [1, 2, 3, 4, 5, 7, 8])
def test_rounds_are_the_operator(spark, h):
    r = random.Random(h)
    n = 24
    edges = [(r.randrange(n), r.randrange(n)) for _ in range(26)]
    edges = [(a, b) for a, b in edges if a != b]
    state, df = {v: v for v in range(n)}, mapping.init_labels(spark.range(n))
    g = made(spark, edges, n)
    for _ in range(3):
        state = literal_round(state, edges, h)
        df = spark.createDataFrame([(x.id, x.label) for x in mapping.apply_min_mapping(g.edges, df, h).collect()], "id bigint, label bigint")
        assert {x.id: x.label for x in df.collect()} == state


def test_hand_made_path(spark):
    g, df = made(spark, [(i, i + 1) for i in range(4)], 5), mapping.init_labels(spark.range(5))
    for want in ([0, 0, 1, 2, 3], [0, 0, 0, 0, 1], [0, 0, 0, 0, 0]):
        df = spark.createDataFrame([(x.id, x.label) for x in mapping.apply_min_mapping(g.edges, df, 2).collect()], "id bigint, label bigint")
        assert [x.label for x in df.orderBy("id").collect()] == want


def test_order_one_is_label_propagation(spark):
    n, edges = GRAPHS["mixed"]
    a, b = (connected_components(made(spark, edges, n), m, early_check="off") for m in ("order1", "label_propagation"))
    assert a.iterations == b.iterations and labels(a) == labels(b)


def test_hooking_rounds_are_synchronous_rounds(spark):
    n, edges = GRAPHS["mixed"]
    a, b = (connected_components(made(spark, edges, n), m) for m in ("sync2", "hook_compress"))
    assert [t[4] for t in a.trace] == [t[4] for t in b.trace]


def test_no_edges(spark):
    r = connected_components(made(spark, [(1, 1)], 3), "order2")
    assert labels(r) == {0: 0, 1: 1, 2: 2} and r.iterations == 0


def test_big_and_negative_ids(spark):
    big = 1 << 61
    g = Graph.from_edges(spark.createDataFrame([(big, -5), (big + 1, big)], "src bigint, dst bigint"))
    assert labels(connected_components(g)) == {-5: -5, big: -5, big + 1: -5}


def test_wrong_input(spark):
    with pytest.raises(TypeError):
        Graph.from_edges(spark.createDataFrame([("a", "b")], "src string, dst string"))
    with pytest.raises(ValueError):
        Graph.from_edges(spark.createDataFrame([(1, None)], "src bigint, dst bigint"), check=True)
    with pytest.raises(ValueError):
        connected_components(made(spark, [(0, 1)], 2), "nothing")
    with pytest.raises(NotConverged):
        connected_components(made(spark, [(i, i + 1) for i in range(9)], 10), "order1", max_iterations=2)


def test_tree_heights_shrink(spark):
    for height in (5, 9):
        path = spark.createDataFrame([(i, max(i - 1, 0)) for i in range(height + 1)], "id bigint, label bigint")
        edges = spark.createDataFrame([(i, i + 1) for i in range(height)], "src bigint, dst bigint")
        for h in (2, 3):
            new = mapping.apply_min_mapping(edges, path, h)
            assert max(r.height for r in mapping.tree_heights(new).collect()) <= mapping.height_after(height, h)


def test_bound_and_height_sums(spark):
    n, ids = 30, list(range(1, 30))
    random.Random(2).shuffle(ids)
    ids = [0, *ids]
    g = made(spark, list(zip(ids, ids[1:])), n)
    assert connected_components(g, "sync2", early_check="eager").iterations <= measures.iteration_bound(measures.diameter(g))
    for k, total in measures.root_tree_sums(g):
        assert 1.5 ** (k - 1) * total <= n - 1


def test_lost_updates_are_repaired(spark):
    n, edges = GRAPHS["mixed"]
    g, r = made(spark, edges, n), random.Random(1)
    state = {v: v for v in range(n)}
    for _ in range(60):
        new = literal_round(state, edges, 2)
        state = {v: x if r.random() > 0.3 else state[v] for v, x in new.items()}
        if all(state[a] == state[b] for a, b in edges):
            break
    assert state == labels(connected_components(g))


def test_edges_stay_where_they_are(spark):
    from minlabel.session import stored

    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        g = made(spark, [(i, (i * 3 + 1) % 50) for i in range(50)], 50)
        state = stored(mapping.init_labels(g.vertices))
        out = mapping.step(g.prepared(4), state, 1)
        plan = out._jdf.queryExecution().executedPlan().toString()
        head = plan.split("Scan ExistingRDD")[0]
        assert "CartesianProduct" not in plan and "NestedLoop" not in plan and "Python" not in plan
        assert head.rstrip().splitlines()[-1].count("Exchange") == 0
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


@pytest.mark.parametrize("method,options", [("sync2", {}), ("order1", {}), ("order2", {"retire": True}), ("chained", {}), ("hook_compress", {}), ("bfs", {})])
def test_hubs_are_parted(spark, method, options):
    """A star of 3000 edges beside a path: no partition holds more than a few parts of the hub, labels are the same, and a round leaves the edges where they are."""
    edges = [(0, i) for i in range(1, 3000)] + [(5000 + i, 5001 + i) for i in range(6)]
    g = made(spark, edges, 5010)
    directed = g.prepared(16, hub_rows=100)
    assert [(r.src, r.salts) for r in directed._hubs.collect()] == [(0, 30)]  # 2999 edges, 100 to a part
    assert max(directed.rdd.mapPartitions(lambda rows: [sum(1 for _ in rows)]).collect()) < 1200
    heads = directed.where("src = 0").groupBy("salt").count().collect()
    assert len(heads) == 30 and max(r["count"] for r in heads) < 200
    got = connected_components(g, method, num_partitions=16, **options)
    assert labels(got) == union_find(range(5010), edges)


@pytest.mark.parametrize("method,options", [("chained", {"blocks": 2}), ("sync2", {}), ("orderm", {"update": "sync", "order": 5})])
def test_rounds_without_broadcasts(spark, method, options):
    """As on large tables, all joins of a round are of tables dealt by id: candidates that go up the pointers still meet in one partition."""
    names = ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold")
    for name in names:
        spark.conf.set(name, "-1")
    try:
        g = WORKLOADS["customer_order"].build(spark, SMOKE)
        got = connected_components(g, method, **options).labels
        assert rows(got) == rows(connected_components(g, "union_find").labels)
    finally:
        for name in names:
            spark.conf.unset(name)


def test_chains_of_one_large_group(spark):
    """Ties go by id, null groups and orders are groups and orders of their own, repeated rows are one."""
    from minlabel.graph import chain_graph

    rows = [(1, "a", 5), (2, "a", 5), (3, "a", 1), (4, "b", 2), (5, "b", None), (6, None, 1), (7, None, 2), (7, None, 2), (8, "c", 1)]
    g = chain_graph(spark.createDataFrame(rows, "e bigint, k string, t int"), "e", ["t"], "k")
    assert sorted((r.src, r.dst) for r in g.edges.collect()) == [(1, 2), (1, 3), (4, 5), (6, 7)]
    assert sorted(r.id for r in g.vertices.collect()) == list(range(1, 9))


def test_in_place_rounds(spark):
    """Many small blocks: labels, fewer edges each round, and orders that differ."""
    r = random.Random(9)
    ids = list(range(200))
    r.shuffle(ids)
    edges = list(zip(ids, ids[1:120])) + [(ids[150], v) for v in ids[151:199]] + [(ids[0], ids[0]), (ids[3], ids[4])]
    g, want = made(spark, edges, 201), union_find(range(201), edges)
    for order in (1, 2, 1024):
        for sweeps in (1, 0):
            got = connected_components(g, "schedule", orders=[order], block_edges=7, local_sweeps=sweeps)
            assert labels(got) == want
            assert got.trace[-1][5] == 0 and all(a[5] > b[5] for a, b in zip(got.trace, got.trace[1:]))


def test_block_kernels():
    import numpy as np
    import pyarrow as pa

    from minlabel.operators import kernels

    r = np.random.default_rng(2)
    a, b = r.integers(0, 400, 500), r.integers(0, 400, 500)
    want = union_find({*a.tolist(), *b.tolist()}, list(zip(a.tolist(), b.tolist())))
    batches = [pa.RecordBatch.from_arrays([pa.array(a[k : k + 50]), pa.array(b[k : k + 50])], names=["src", "dst"]) for k in range(0, 500, 50)]
    for order in (1, 2, 5, 1024):
        for sweeps in (0, 1):
            rows = pa.Table.from_batches(kernels.thinning_kernel(order, sweeps, 120)(batches)).to_pylist()
            links = [(x["id"], x["down"]) for x in rows if x["down"] is not None]
            assert all(x >= y for x, y in links) and union_find(want, links) == want
            assert {x["id"] for x in rows if x["down"] is None} >= {y for x, y in links if y < x}
    got = {}
    for batch in kernels.forest_kernel(1000)(batches):
        got |= dict(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()))
    assert got == want


def test_contradictory_options(spark):
    g = made(spark, [(0, 1)], 2)
    for method, options in (("orderm", {"orders": [1]}), ("order2", {"order": 5}), ("sync2", {"update": "in_place"}), ("order2", {"update": "in_place", "retire": True}), ("block_async", {"update": "sync"}), ("order2", {"update": "later"})):
        with pytest.raises(ValueError):
            connected_components(g, method, **options)


@pytest.mark.parametrize("method", ["sync2", "order1", "hook_compress"])
@pytest.mark.parametrize("graph", ["order_part_sparse", "event_value_chain"])
def test_rounds_in_one_task(spark, graph, method):
    """Rounds made in one task are those that are dealt out: same labels, changes and vertices left."""
    if graph == "event_value_chain" and method == "order1":
        g = generate(spark, "random", 60, 3, 0.9)
    else:
        g = WORKLOADS[graph].build(spark, SMOKE)
    far, near = connected_components(g, method), connected_components(g, method, local_edges=1 << 20)
    assert [r[:7] for r in near.trace] == [r[:7] for r in far.trace]
    assert (near.iterations, near.edge_passes) == (far.iterations, far.edge_passes)
    assert rows(near.labels) == rows(far.labels)


def test_similar_pairs_are_thinned(spark):
    """All pairs over the threshold are edges, whatever the blocks; what the rounds read are fewer that connect the same. Vectors without a partner, of another length, or null, keep their own label."""
    r = random.Random(4)
    vectors = [(k, [r.gauss(0, 1) + (k % 3 == c) for c in range(6)]) for k in range(120)] + [(120, None), (121, [1.0, 2.0]), (122, [0.0] * 6), (123, [1.0, None])]
    dot = lambda a, b: sum(x * y for x, y in zip(a, b))
    full = [(k, v) for k, v in vectors if v and len(v) == 6]
    want = sorted((a, b) for a, x in full for b, y in full if a < b and dot(x, y) > 0.8 * dot(x, x) ** 0.5 * dot(y, y) ** 0.5)
    df = spark.createDataFrame(vectors, "id bigint, v array<double>")
    for blocks in (1, 3):
        g = similarity_graph(df, "id", "v", 0.8, blocks)
        assert sorted(map(tuple, g.edges.collect())) == want
        assert g.raw.count() < len(want)
        got = {x.id: x.label for x in connected_components(g).labels.collect()}
        assert got == union_find([k for k, _ in vectors], want)


def test_kept_graphs_and_hops_in_one_task(spark):
    """A kept graph has the vertices and labels of the one that it is made from, loops, repetitions and single ends included, and following pointers in one task changes nothing."""
    edges = [(k * 37 % 101, (k + 1) * 37 % 101) for k in range(100)] + [(200, 200), (3, 3), (5, 9), (9, 5), (None, 300), (301, None)]
    g = made(spark, edges, 102)
    kept = g.kept()
    assert rows(kept.vertices) == rows(g.vertices) and kept.rows == 102 and kept._stored is None
    want = labels(connected_components(g, "order2"))
    for options in ({"orders": [1024]},):
        far, near = (connected_components(kept, "schedule", block_edges=20, local_sweeps=1, local_edges=n, **options) for n in (0, 1000))
        assert [r[:7] for r in near.trace] == [r[:7] for r in far.trace] and len(near.trace) > 1
        assert rows(near.labels) == rows(far.labels) and labels(near) == want and near.labels.count() == len(want)
    assert labels(connected_components(kept, "union_find", num_partitions=4)) == want


def test_many_pairs_are_joined_at_once():
    """A large block in arrays: a path of shuffled ids, too slow pair by pair in Python."""
    import time

    import numpy as np

    from minlabel.operators import kernels

    ids = np.random.default_rng(5).permutation(1 << 20) * 3 - 7
    began = time.process_time()
    got = kernels.block_minima(np.concatenate([ids[:-1], [5000000]]), np.concatenate([ids[1:], [4000000]]))
    assert time.process_time() - began < 60 and got[0].tolist()[-1] == 5000000
    assert set(got[1].tolist()) == {-7, 4000000}


def test_graphs_of_experiments_are_written_once(spark):
    from minlabel.plans import experiments
    from minlabel.workloads import graph_catalog

    g = experiments.built(spark, SMOKE, "event_user_chain")
    other = experiments.built(spark, SMOKE, "order_part_sparse")
    assert experiments.built(spark, SMOKE, "event_user_chain") is g and experiments.built(spark, SMOKE, "order_part_sparse") is other
    names = ["order_part_sparse", "event_user_chain"]
    assert rows(graph_catalog(spark, SMOKE, names, experiments.built)) == rows(graph_catalog(spark, SMOKE, names))
    assert all("FileScan" not in line or "events" not in line for line in g.raw._jdf.queryExecution().executedPlan().toString().splitlines())


def test_chains_across_ranges(spark):
    """Rows next to each other in different ranges, with empty ranges between, are linked."""
    from minlabel.graph import chain_graph

    g = chain_graph(spark.range(0, 40, 1, 3).selectExpr("id as e", "cast(id % 5 as double) as t"), "e", ["t"], None)
    order = sorted(range(40), key=lambda k: (k % 5, k))
    assert sorted((r.src, r.dst) for r in g.edges.collect()) == sorted((min(p), max(p)) for p in zip(order, order[1:]))
