"""Writers, and a store of rounds that a broken run goes on from."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_labels(labels: DataFrame, path: str, mode: str = "overwrite", by: str | None = None) -> None:
    (labels.write.mode(mode).partitionBy(by) if by else labels.write.mode(mode)).parquet(path)


def write_bucketed(df: DataFrame, name: str, column: str, buckets: int) -> None:
    """A table whose rows of one key lie in one bucket, so that joins on the key need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, column).sortBy(column).saveAsTable(name)


class CheckpointStore:
    """Rounds of a run in a shared folder. A round counts once its table has Spark's own mark of success."""

    def __init__(self, path: str):
        self.path = path.rstrip("/")

    def save(self, k: int, labels: DataFrame) -> None:
        labels.write.mode("overwrite").parquet(f"{self.path}/round={k:06d}")

    def latest(self, spark: SparkSession) -> tuple[int, DataFrame] | None:
        root = spark._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
        if not fs.exists(root):
            return None
        found = [str(s.getPath()) for s in fs.listStatus(root)]
        done = [(int(m[1]), p) for p in found if (m := re.search(r"round=(\d+)$", p)) and fs.exists(spark._jvm.org.apache.hadoop.fs.Path(f"{p}/_SUCCESS"))]
        if not done:
            return None
        k, p = max(done)
        return k, spark.read.parquet(p).select(F.col("id").cast("bigint").alias("id"), F.col("label").cast("bigint").alias("label"))
