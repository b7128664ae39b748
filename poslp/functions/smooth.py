"""Smoothed extrema of a column, without overflow and in one pass with map-side combine.

exp(eta v) overflows doubles from eta v = 709 on, so values are summed in buckets of eta v of width 256, each relative
to its bucket; a handful of buckets reach the driver and are merged there in logarithms.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WIDTH = 256.0


def log_sum_exp(df: DataFrame, value: Column, eta: float) -> float:
    """ln sum exp(eta value); minus infinity for no rows; nulls are left out."""
    v = value.cast("double") * F.lit(float(eta))
    k = F.floor(v / F.lit(WIDTH))
    rows = df.where(value.isNotNull()).groupBy(k.alias("k")).agg(F.sum(F.exp(v - k * F.lit(WIDTH))).alias("s")).collect()
    parts = [r["k"] * WIDTH + math.log(r["s"]) for r in rows]
    top = max(parts, default=-math.inf)
    return top + math.log(sum(math.exp(p - top) for p in parts)) if parts else top


def smax(df: DataFrame, col: str, eta: float) -> float:
    return log_sum_exp(df, F.col(col), eta) / eta


def smin(df: DataFrame, col: str, eta: float) -> float:
    return -log_sum_exp(df, -F.col(col), eta) / eta


def grad_smax(df: DataFrame, col: str, eta: float, name: str = "weight") -> DataFrame:
    """Adds the softmax weights of eta col, which sum to one."""
    shift = log_sum_exp(df, F.col(col), eta)
    return df.withColumn(name, F.exp(F.col(col) * F.lit(float(eta)) - F.lit(shift)))


def grad_smin(df: DataFrame, col: str, eta: float, name: str = "weight") -> DataFrame:
    shift = log_sum_exp(df, -F.col(col), eta)
    return df.withColumn(name, F.exp(-F.col(col) * F.lit(float(eta)) - F.lit(shift)))


def stats(df: DataFrame, cols: list[str]) -> dict[str, dict[str, float]]:
    """Maximum, minimum, sum and count of each column from one aggregate."""
    aggs = [f(c).alias(f"{n}_{i}") for i, c in enumerate(cols) for n, f in (("max", F.max), ("min", F.min), ("sum", F.sum), ("count", F.count))]
    r = df.agg(*aggs).first()
    return {c: {n: r[f"{n}_{i}"] for n in ("max", "min", "sum", "count")} for i, c in enumerate(cols)}


def potential(packing: DataFrame, y: str, covering: DataFrame, z: str, eta: float) -> float:
    return smax(packing, y, eta) - smin(covering, z, eta)
