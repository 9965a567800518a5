"""Sources, sinks, ids, SQL surface and streams."""

import datetime

from pyspark.sql import functions as F

from minlabel import ids
from minlabel.functions import sql
from minlabel.plans import advisor
from minlabel.plans.engine import connected_components
from minlabel.sources import edges, sinks
from minlabel.sources.matrix import MatrixSource
from minlabel.streaming import incremental
from minlabel.workloads import WORKLOADS, generate
from tests.conftest import SMOKE


def pairs(df):
    return sorted((r.src, r.dst) for r in df.collect())


def test_edge_files(spark, tmp_path):
    g = WORKLOADS["order_part_sparse"].build(spark, SMOKE)
    want = pairs(g.edges)
    text = tmp_path / "edges.txt"
    text.write_text("# comment\n% another\n" + "".join(f"{a + 1} {b + 1}\n" for a, b in want))
    assert pairs(edges.read_edge_list(spark, str(text), base=1)) == want
    matrix = tmp_path / "m.mtx"
    matrix.write_text("%%MatrixMarket\n% c\n9999 9999 " + f"{len(want)}\n" + "".join(f"{a + 1} {b + 1} 1.0\n" for a, b in want))
    assert pairs(edges.read_matrix_coordinates(spark, str(matrix))) == want
    spark.dataSource.register(MatrixSource)
    assert pairs(spark.read.format("matrix_coo").option("partitionbytes", "200").load(str(matrix))) == want
    for fmt in ("csv", "json", "orc", "parquet"):
        out = str(tmp_path / fmt)
        w = g.edges.write
        (w.option("header", True) if fmt == "csv" else w).format(fmt).save(out)
        assert pairs(edges.read_edges(spark, out, fmt)) == want
    g.edges.createOrReplaceTempView("some_edges")
    assert pairs(edges.graph_from_sql(spark, "select src, dst from some_edges").edges) == want


def test_store_goes_on(spark, tmp_path):
    g = generate(spark, "path", 40)
    store = sinks.CheckpointStore(str(tmp_path / "rounds"))
    full = connected_components(g, "order2", store=store)
    k, _ = store.latest(spark)
    assert k == full.iterations
    again = connected_components(g, "order2", store=store)
    assert again.iterations >= k and {r.label for r in again.labels.collect()} == {0}
    sinks.write_labels(full.labels, str(tmp_path / "labels"))
    assert spark.read.parquet(str(tmp_path / "labels")).count() == 40


def test_ids(spark):
    df = spark.createDataFrame([("b", "x"), ("a", "y"), (None, "x")], "l string, r string")
    out, vocabulary = ids.encode_ids(df, {"l": "left", "r": "right"})
    assert sorted((v.kind, v.key, v.id) for v in vocabulary.collect()) == [("left", "a", 0), ("left", "b", 1), ("right", "x", 2), ("right", "y", 3)]
    assert sorted((r.l is None, r.l or 0, r.r) for r in out.collect()) == [(False, 0, 3), (False, 1, 2), (True, 0, 2)]
    labels = spark.createDataFrame([(0, 0), (3, 0)], "id bigint, label bigint")
    assert sorted(tuple(r) for r in ids.decode_labels(labels, vocabulary).collect()) == [("left", "a", "left", "a"), ("right", "y", "left", "a")]


def test_generators(spark):
    for kind, parts in (("path", 1), ("cycle", 1), ("star", 1), ("clique", 1), ("forest", 4)):
        r = connected_components(generate(spark, kind, 28), "order2")
        assert r.labels.select("label").distinct().count() == parts, kind


def test_sql_surface(spark):
    sql.register_sql(spark)
    assert [r[0] for r in spark.sql("select min_map_bound(d) from values (1L), (4L), (127L) t(d) order by d").collect()] == [2, 5, 13]
    assert sorted(tuple(r) for r in spark.sql("select src, dst from edges_of_row('1 2 3')").collect()) == [(1, 2), (2, 3)]
    assert spark.sql("select component_min(v) from values (3L), (2L) t(v)").first()[0] == 2
    sql.register_result(connected_components(generate(spark, "path", 5)).labels)
    assert spark.sql("select size from components_sizes").first()[0] == 5


def test_advice():
    stats = {"n": 100, "m": 100, "diameter_lb": 3}
    assert advisor.recommend_method(stats, 4).method == "order1"
    assert advisor.recommend_method(stats | {"diameter_lb": 20}, 4).method == "order2"
    assert advisor.recommend_method(stats | {"diameter_lb": 2000}, 4).method == "orderm"
    assert advisor.recommend_method(stats, 4, 0.9).method == "low_then_high"
    assert advisor.recommend_method(stats, 4, 0.4).method == "alternate"
    assert advisor.recommend_method(stats | {"m": 10**10}, 4).method == "union_find"


def test_streams(spark, tmp_path):
    events = spark.read.parquet(f"{SMOKE}/events.parquet").orderBy("ts").limit(300)
    rows = [r for r in events.select("event_id", "ts", "user_id", "event_type").collect()]
    schema = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string"
    source = str(tmp_path / "in")
    for k in range(3):
        spark.createDataFrame(rows[100 * k : 100 * k + 100], schema).coalesce(1).write.mode("append").parquet(source)
    chain = incremental.chain_edges(incremental.read_event_stream(spark, source, schema))
    chain.writeStream.format("memory").queryName("chain").option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start().awaitTermination()
    got = spark.table("chain")
    last, want = {}, set()
    for r in rows:
        if r.user_id in last:
            want.add((last[r.user_id], r.event_id))
        last[r.user_id] = r.event_id
    assert set(pairs(got)) == want
    out = str(tmp_path / "edges")
    got.coalesce(1).write.parquet(out)
    store = sinks.CheckpointStore(str(tmp_path / "labels"))
    stream = spark.readStream.schema("src bigint, dst bigint").parquet(out)
    incremental.start_incremental(stream, store, str(tmp_path / "c2")).awaitTermination()
    labels = {r.id: r.label for r in store.latest(spark)[1].collect()}
    least = {}
    for r in rows:
        least[r.user_id] = min(least.get(r.user_id, r.event_id), r.event_id)
    user = {r.event_id: r.user_id for r in rows}
    assert labels and all(v == least[user[k]] for k, v in labels.items())
    # a batch again changes nothing; removing an edge splits
    same = incremental.absorbed(store.latest(spark)[1], got)
    assert {r.id: r.label for r in same.collect()} == labels
    a, b = max(want)
    left = got.where(~((F.col("src") == a) & (F.col("dst") == b)))
    cut = {r.id: r.label for r in incremental.recomputed(store.latest(spark)[1], left, spark.createDataFrame([(a, b)], "src bigint, dst bigint")).collect()}
    assert cut[b] == b and cut[a] == labels[a]


def test_stream_windows(spark, tmp_path):
    day = datetime.datetime(2024, 1, 1)
    rows = [(i, day + datetime.timedelta(hours=h), u, "x") for i, (h, u) in enumerate([(0, 1), (1, 1), (9, 1), (20, 2), (21, 2), (21, 2), (60, 1)])]
    schema = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string"
    spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / "in"))
    read = lambda: incremental.read_event_stream(spark, str(tmp_path / "in"), schema)

    def run(df, name, mode="append"):
        df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
        return spark.table(name)

    assert sorted(r.n for r in run(incremental.windowed_users(read()), "w", "complete").collect()) == [1, 6]
    assert sorted(r.n for r in run(incremental.session_counts(read()), "s", "complete").collect()) == [1, 1, 2, 3]
    assert run(incremental.without_repeats(read()), "d").count() == 7
    assert (0, 1) in pairs(run(incremental.paired(read(), read()), "p"))


def test_long_conversations_stay_apart(spark, tmp_path):
    rows = [(1, t) for t in range(1003)] + [(2, t) for t in range(3)]
    spark.createDataFrame(rows, "conv_id bigint, turn int").write.parquet(f"{tmp_path}/conversations.parquet")
    from minlabel import catalog

    got = [tuple(r) for r in catalog.components(spark, str(tmp_path), "conversation_chain", "union_find").collect()]
    assert sorted(got) == sorted((c * 1000 + t, c * 1000) for c, t in rows)


def test_short_benchmark_items(spark, tmp_path):
    docs, items = [(1, "a short text here"), (2, "one two three four five six seven"), (3, None)], [(1, "short text"), (2, "two three four five six"), (3, "sev"), (4, ""), (5, None), (6, "absent")]
    spark.createDataFrame(docs, "doc_id bigint, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(items, "item_id bigint, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    from minlabel.workloads import benchmark_doc

    got = {tuple(sorted(r)) for r in benchmark_doc(spark, str(tmp_path)).edges.collect()}
    assert got == {tuple(sorted((d * 2, i * 2 + 1))) for d, t in docs for i, x in items if None not in (t, x) and x in t}


def test_sessions_of_distant_users_overlap(spark, tmp_path):
    spark.sql("select * from values (1L, 1L, timestamp '2024-01-01 23:00:00'), (2L, 9L, timestamp '2024-01-01 22:00:00'), (3L, 9L, timestamp '2024-01-02 01:00:00'), (4L, 5L, timestamp '2024-03-01 00:00:00') t(event_id, user_id, ts)").write.parquet(f"{tmp_path}/events.parquet")
    from minlabel import relational

    assert [tuple(r) for r in relational.session_overlap_all_users(spark, str(tmp_path)).collect()] == [(1, 9, 1)]
