"""What the engine needs from a running session: a shared folder for cut lineage, and tables by name."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession


def checkpoint_root(spark: SparkSession) -> str:
    """The shared folder that the cluster names in spark.checkpoint.dir; a temporary one only where it is unset (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        if spark.sparkContext.getCheckpointDir() is None:
            spark.sparkContext.setCheckpointDir(named)
        return named.rstrip("/")
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="minlabel-"))
    return spark.sparkContext.getCheckpointDir().rstrip("/")


def checkpoint(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: keeps the partitioning, survives lost executors, cuts the lineage."""
    checkpoint_root(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame, name: str = "labels") -> DataFrame:
    """df written as a Parquet table in the shared folder and read again: cut lineage with columns still prunable, and with sizes that the planner can trust.

    A checkpoint() would keep the partitioning, but also the size that was estimated for its plan; over the rounds of a
    loop these estimates multiply into numbers that take the planner minutes. The folder goes when the driver ends.
    """
    spark = df.sparkSession
    path = f"{_own_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stored_at = path
    if (made := _collected.get()) is not None:
        made.append(out)
    return out


_collected: ContextVar[list | None] = ContextVar("collected", default=None)


def collect_stored() -> list:
    """From here on, the tables that stored() writes, until discard_collected()."""
    made: list = []
    _collected.set(made)
    return made


def discard_collected(made: list, *kept: DataFrame) -> None:
    """Remove the collected tables, but for those that are kept."""
    _collected.set(None)
    for df in made:
        if not any(df is k for k in kept):
            discard(df)


class Scratch:
    """Tables that are stored on the way to a result, to be removed together once the result itself is stored."""

    def __init__(self):
        self.held: list[DataFrame] = []

    def stored(self, df: DataFrame, name: str = "labels") -> DataFrame:
        self.held.append(stored(df, name))
        return self.held[-1]

    def clear(self) -> None:
        for df in self.held:
            discard(df)
        self.held = []


def discard(df: DataFrame) -> None:
    """Remove what stored() wrote for this very DataFrame, when nothing reads it any more."""
    if path := getattr(df, "_stored_at", None):
        _remove(df.sparkSession, path)


_folders: dict[str, str] = {}


def _own_folder(spark: SparkSession) -> str:
    root = checkpoint_root(spark)
    if root not in _folders:
        _folders[root] = f"{root}/minlabel-{uuid.uuid4().hex}"
        atexit.register(_remove, spark, _folders[root])
    return _folders[root]


def _remove(spark: SparkSession, path: str) -> None:
    try:
        target = spark._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # the session may be gone already; the folder is then left to the cluster's own cleaning
        return


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
