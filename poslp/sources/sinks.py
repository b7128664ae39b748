"""Sinks: edge tables by graph, bucketed vertex and edge tables that join without a shuffle, and traces that grow."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_partitioned(df: DataFrame, path: str, *by: str, mode: str = "overwrite") -> DataFrame:
    """Parquet in a folder for each value of the columns; reading with a filter on them opens those folders alone. Rows are
    first brought together by folder, and spread inside it by their content, so that a hot folder is no single task."""
    spread = F.pmod(F.xxhash64(*df.columns), F.lit(16))
    df.repartition(*by, spread).write.mode(mode).partitionBy(*by).parquet(path)
    return df.sparkSession.read.parquet(path)


def write_bucketed(df: DataFrame, name: str, path: str, by: str, buckets: int) -> DataFrame:
    """A catalog table at the path, bucketed and sorted by a column. Tables of equal bucket counts join on it in place."""
    df.repartition(buckets, by).write.mode("overwrite").option("path", path).bucketBy(buckets, by).sortBy(by).saveAsTable(name)
    return df.sparkSession.table(name)


def append_trace(trace: DataFrame, path: str, run: str, graph: str, problem: str) -> None:
    """Adds a solve's iterations to a table by graph and problem. A repeated run replaces its own rows' folder."""
    rows = trace.withColumns({"graph": F.lit(graph), "problem": F.lit(problem), "run": F.lit(run)})
    rows.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("graph", "problem", "run").parquet(path)


def write_report(report: DataFrame, path: str) -> None:
    """A report of few rows as CSV with a header, in one file."""
    report.coalesce(1).write.mode("overwrite").option("header", True).csv(path)
