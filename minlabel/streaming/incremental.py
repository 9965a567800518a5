"""Components of a growing edge stream, and the streaming operators around it.

Labels only go down and are minima, so a batch that comes twice changes nothing. Removing edges needs the stored edges of
the components it touches: those are computed anew (see recomputed)."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery

from minlabel.graph import Graph, canonical_edges
from minlabel.operators.mapping import moved
from minlabel.plans.engine import connected_components, contracted_edges
from minlabel.sources.sinks import CheckpointStore


def read_event_stream(spark: SparkSession, path: str, schema, files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def absorbed(labels: DataFrame, edges: DataFrame) -> DataFrame:
    """Labels after more edges: the batch is replaced by edges between labels, that small graph is solved, and labels that changed are looked up once. Its cost follows the batch but for one pass over the labels."""
    fresh = edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct().join(labels, "id", "left_anti").select("id", F.col("id").alias("label"))
    known = labels.unionByName(fresh)
    over = contracted_edges(canonical_edges(edges), known)
    if over.isEmpty():
        return known
    solved = connected_components(Graph.from_edges(over), "order2").labels
    return moved(known, "label", solved).select("id", "label")


def start_incremental(edges: DataFrame, store: CheckpointStore, checkpoint_location: str) -> StreamingQuery:
    """A query that keeps the labels of a stream of (src, dst) in the store, a round for each batch; a batch that was done is skipped."""
    spark = edges.sparkSession

    def batch(df: DataFrame, k: int) -> None:
        kept = store.latest(spark)
        if kept and kept[0] > k:
            return
        labels = kept[1] if kept else spark.createDataFrame([], "id bigint, label bigint")
        store.save(k + 1, absorbed(labels, df))

    return edges.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint_location).trigger(availableNow=True).start()


def recomputed(labels: DataFrame, edges: DataFrame, removed: DataFrame) -> DataFrame:
    """Labels after edges were removed: edges are those that are left; only components that lost one are solved again."""
    touched = removed.select(F.explode(F.array("src", "dst")).alias("id")).join(labels, "id").select("label").distinct()
    part = labels.join(touched, "label", "left_semi").select("id")
    inner = edges.join(part.withColumnRenamed("id", "src"), "src", "left_semi")
    solved = connected_components(Graph.from_edges(inner, part), "order2").labels
    return labels.join(touched, "label", "left_anti").select("id", "label").unionByName(solved)


def chain_edges(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """(src, dst) of consecutive events of a user, as they come: the state is each user's last event."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])["event_id"].tolist()
        ids = ([last] if last is not None else []) + rows
        state.update((ids[-1],))
        yield pd.DataFrame({"src": ids[:-1], "dst": ids[1:]}, dtype="int64")

    given = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)
    return given.select("user_id", "event_id", "ts").groupBy("user_id").applyInPandasWithState(step, "src bigint, dst bigint", "last bigint", "append", "NoTimeout")


def windowed_users(events: DataFrame, width: str = "1 day", slide: str | None = None, lateness: str = "1 hour") -> DataFrame:
    """Events and users (estimated) in tumbling or sliding windows; rows later than the watermark are left out."""
    given = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)
    return given.groupBy(F.window("ts", width, slide) if slide else F.window("ts", width)).agg(F.count("*").alias("n"), F.approx_count_distinct("user_id").alias("users"))


def session_counts(events: DataFrame, gap: str = "6 hours", lateness: str = "1 hour") -> DataFrame:
    given = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)
    return given.groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))


def without_repeats(events: DataFrame, key: str = "event_id", lateness: str = "1 hour") -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness).dropDuplicatesWithinWatermark([key])


def paired(left: DataFrame, right: DataFrame, within: str = "1 hour") -> DataFrame:
    """Events of one stream with later ones of the same user in another, within an interval."""
    a = left.select(F.col("user_id").alias("u"), F.col("event_id").alias("src"), F.col("ts").cast("timestamp").alias("ta")).withWatermark("ta", within)
    b = right.select(F.col("user_id").alias("v"), F.col("event_id").alias("dst"), F.col("ts").cast("timestamp").alias("tb")).withWatermark("tb", within)
    return a.join(b, F.expr(f"u = v and tb > ta and tb <= ta + interval {within}")).select("src", "dst")
