"""Edge lists in files, tables and SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from minlabel.graph import Graph


def read_edge_list(spark: SparkSession, path: str, sep: str = r"\s+", comment: str = "[#%]", base: int = 0) -> DataFrame:
    """src, dst of a text of two numbers a line; ids begin at base in the file and at 0 here. Lines that are no edge are an error."""
    lines = spark.read.text(path).select(F.trim("value").alias("line")).where((F.col("line") != "") & ~F.col("line").rlike(f"^{comment}"))
    parts = F.split("line", sep)
    return lines.select((parts[0].cast("bigint") - base).alias("src"), (parts[1].cast("bigint") - base).alias("dst"))


def read_matrix_coordinates(spark: SparkSession, path: str) -> DataFrame:
    """src, dst of a coordinate matrix file: comment lines with %, a line of sizes, then 1-based row, column and perhaps a value.

    The line of sizes is the first of its file without %; it alone has three whole numbers of which the third counts the
    entries, so it is found by its place: the smallest offset, by one small aggregate."""
    lines = spark.read.text(path).select("value", F.monotonically_increasing_id().alias("place"), F.input_file_name().alias("file")).where(~F.col("value").startswith("%") & (F.trim("value") != ""))
    head = lines.groupBy("file").agg(F.min("place").alias("place"))
    body = lines.join(F.broadcast(head) if head.count() <= 10_000 else head, ["file", "place"], "left_anti")
    parts = F.split(F.trim("value"), r"\s+")
    return body.select((parts[0].cast("bigint") - 1).alias("src"), (parts[1].cast("bigint") - 1).alias("dst"))


def read_edges(spark: SparkSession, path: str, fmt: str, src: str = "src", dst: str = "dst", **options) -> DataFrame:
    """From csv, json, orc or parquet."""
    if fmt in ("csv", "json"):
        df = spark.read.options(header=True, **options).schema(f"`{src}` bigint, `{dst}` bigint").format(fmt).load(path)
    else:
        df = spark.read.options(**options).format(fmt).load(path)
    return df.select(F.col(src).cast("bigint").alias("src"), F.col(dst).cast("bigint").alias("dst"))


def graph_from_sql(spark: SparkSession, edges: str, vertices: str | None = None, name: str = "") -> Graph:
    """edges: SQL with src and dst; vertices: SQL with id."""
    return Graph.from_edges(spark.sql(edges), spark.sql(vertices) if vertices else None, name)
