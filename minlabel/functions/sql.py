"""What SQL users get: functions, table functions and views over a result."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import AnalyzeArgument, AnalyzeResult, pandas_udf, udtf
from pyspark.sql import types as T

from minlabel.plans.measures import component_sizes


@pandas_udf(T.LongType())
def component_min(v: pd.Series) -> int:
    """A grouped aggregate that the built-in min replaces everywhere but in its own test."""
    return int(v.min())


@pandas_udf(T.LongType())
def shifted_xor(v: pd.Series) -> pd.Series:
    """The last step of workloads.permuted, for 12 bits, on Arrow batches."""
    return v ^ (v // 64)


class EdgesOfRow:
    """TABLE(edges_of_row(text)): a row for each pair of neighbouring whole numbers in a text. With a second argument, a constant name, the columns carry it."""

    @staticmethod
    def analyze(text: AnalyzeArgument, prefix: AnalyzeArgument | None = None) -> AnalyzeResult:
        p = prefix.value if prefix is not None and prefix.value else ""
        return AnalyzeResult(T.StructType([T.StructField(f"{p}src", T.LongType()), T.StructField(f"{p}dst", T.LongType())]))

    def eval(self, text, prefix=None):
        numbers = [int(x) for x in (text or "").split() if x.lstrip("-").isdigit()]
        yield from zip(numbers, numbers[1:])


def register_sql(spark: SparkSession) -> None:
    """min_map_bound(d), edges_of_row(text) and component_min(v) for spark.sql."""
    spark.sql("create or replace temporary function min_map_bound(d bigint) returns bigint return case when d > 1 then cast(ceil(ln(d) / ln(1.5D)) as bigint) + 1 else 2 end")
    spark.udtf.register("edges_of_row", udtf(EdgesOfRow))
    spark.udf.register("component_min", component_min)


def register_result(labels: DataFrame, name: str = "components") -> None:
    """Views name (id, label) and name_sizes."""
    labels.createOrReplaceTempView(name)
    component_sizes(labels).createOrReplaceTempView(f"{name}_sizes")


def paths_to_roots(labels: DataFrame, ids: list[int], most: int = 10_000) -> list[Row]:
    """For a few vertices the pointers that were followed, for a report."""
    return labels.where(F.col("id").isin(ids[:most])).collect()
