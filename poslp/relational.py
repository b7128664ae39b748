"""Relational operators around the methods, on edge tables and events."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def rollup_report(df: DataFrame, dims: list[str], *aggs: Column) -> DataFrame:
    return df.rollup(*dims).agg(*aggs, F.grouping_id().alias("level"))


def cube_report(df: DataFrame, dims: list[str], *aggs: Column) -> DataFrame:
    return df.cube(*dims).agg(*aggs, F.grouping_id().alias("level"))


def top_k(df: DataFrame, group: str, by: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(group).orderBy(*by))).where(F.col("rank") <= k)


def semi_matched(df: DataFrame, matched: DataFrame, key: str) -> DataFrame:
    return df.join(matched.select(key), key, "left_semi")


def anti_isolated(df: DataFrame, used: DataFrame, key: str) -> DataFrame:
    return df.join(used.select(key), key, "left_anti")


def set_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select(*sorted(a.columns)).exceptAll(b.select(*sorted(a.columns)))


def asof(left: DataFrame, right: DataFrame, on: str, by: str, value: str) -> DataFrame:
    """left with the last value of right at or before it, in one sorted pass over both instead of a range join."""
    both = left.select(by, on, F.lit(None).cast(right.schema[value].dataType).alias(value), F.struct(*left.columns).alias("_row"), F.lit(1).alias("_side"))
    both = both.unionByName(right.select(by, on, value, F.lit(None).cast(both.schema["_row"].dataType).alias("_row"), F.lit(0).alias("_side")))
    order = Window.partitionBy(by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("_last", F.last(value, ignorenulls=True).over(order)).where("_side = 1").select("_row.*", F.col("_last").alias(f"last_{value}"))


def interval_join(left: DataFrame, right: DataFrame, on: str, seconds: int) -> DataFrame:
    """Pairs of rows whose times differ by less than so many seconds: an equi-join on buckets and their neighbours."""
    at = lambda c: F.col(c).cast("timestamp").cast("double")
    bucket = F.floor(at(on) / seconds)
    a = left.withColumn("_b", bucket)
    b = right.select(*[F.col(c).alias(f"other_{c}") for c in right.columns], F.explode(F.array(bucket - 1, bucket, bucket + 1)).alias("_b"))
    near = F.abs(at(on) - at(f"other_{on}")) < seconds
    return a.join(b, "_b").where(near).drop("_b")


def sets_report(df: DataFrame, sets: list[list[str]], *aggs: Column) -> DataFrame:
    """Totals of the named sets of dimensions, and of no others."""
    dims = list(dict.fromkeys(c for one in sets for c in one))
    return df.groupingSets([[F.col(c) for c in one] for one in sets], *dims).agg(*aggs, F.grouping_id().alias("level"))


def to_long(df: DataFrame, keys: list[str], values: list[str], name: str, value: str) -> DataFrame:
    return df.unpivot(keys, values, name, value)


def set_intersection(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select(*sorted(a.columns)).intersect(b.select(*sorted(a.columns)))


def salted_sum(df: DataFrame, key: str, value: str, salts: int = 32, *spread: str) -> DataFrame:
    """(key, value) sums in two steps, for sums of which a map-side part would not shrink: first by key and a salt of the
    spread columns, so that no task holds a whole hot key, then by key."""
    salt = F.pmod(F.xxhash64(*(spread or df.columns)), F.lit(salts))
    part = df.groupBy(key, salt.alias("_salt")).agg(F.sum(value).alias(value))
    return part.groupBy(key).agg(F.sum(value).alias(value))


def observed(df: DataFrame, *metrics: Column) -> tuple[DataFrame, Observation]:
    """df and counters that the first action on it fills, without a job of their own."""
    seen = Observation()
    return df.observe(seen, *metrics), seen


def sketched_degrees(edges: DataFrame, by: str, of: str, error: float = 0.02) -> DataFrame:
    """Distinct partners by a sketch of bounded size."""
    return edges.groupBy(by).agg(F.approx_count_distinct(of, error).alias("partners"))
