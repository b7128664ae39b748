"""Graphs from a stream of events: windowed edges, late rows by watermark, a solve per finished window."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from poslp.config import SolveConfig
from poslp.plans.problems import solve

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def window_edges(stream: DataFrame, size: str = "1 day", slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """(start, user_id, event_type, n): user-to-type edges of each window, each edge once."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    counted = stream.withWatermark("ts", watermark).groupBy(window.alias("w"), "user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col("w.start").alias("start"), "user_id", "event_type", "n")


def session_edges(stream: DataFrame, gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    """(start, end, user_id, n): sessions of each user, ended by a gap."""
    counted = stream.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


def unique_edges(stream: DataFrame, watermark: str = "1 hour", width: str = "1 day") -> DataFrame:
    """(ts, start, user_id, event_type): the first row of each edge in each window; the watermark bounds the state."""
    rows = stream.select("ts", F.window("ts", width)["start"].alias("start"), "user_id", "event_type")
    return rows.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["start", "user_id", "event_type"])


def solve_windows(batch: DataFrame, problem: str = "bimatching", cfg: SolveConfig | None = None) -> DataFrame:
    """One report per window of a batch of window_edges. Window starts are few: one per slide of the trigger's span."""
    spark, out = batch.sparkSession, None
    types = batch.select("event_type").distinct()
    types = types.select("event_type", F.pmod(F.xxhash64("event_type"), F.lit(1 << 40)).alias("t"))
    edges = batch.join(F.broadcast(types), "event_type").select("start", (2 * F.col("user_id")).alias("a"), (2 * F.col("t") + 1).alias("b"))
    edges = edges.select("start", F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct()
    for (start,) in batch.select("start").distinct().orderBy("start").toLocalIterator():
        one = solve(problem, edges.where(F.col("start") == F.lit(start)).select("u", "v"), cfg, str(start)).report()
        one = one.select(F.lit(start).alias("start"), "*")
        out = one if out is None else out.unionByName(one)
    return out if out is not None else spark.createDataFrame([], "start timestamp, problem string, graph string, eps double, status string, objective double, lower double, upper double, max_violation double, iters long")


def solve_each_window(stream: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str, problem: str = "bimatching", cfg: SolveConfig | None = None) -> StreamingQuery:
    """Solves each window once it is closed and hands the reports to the sink with the batch id, which makes repeats
    recognisable."""
    return window_edges(stream).writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(lambda b, k: sink(solve_windows(b, problem, cfg), k)).trigger(availableNow=True).start()
