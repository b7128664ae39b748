"""Density by peeling: one least-degree vertex at a time (half the optimum), or all low-degree vertices per pass."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poslp.baselines.matching import neighbours
from poslp.plans.shared import materialise


#: Degree of a vertex that is gone; what is taken off it later never counts.
GONE = 1 << 60


def peel_sequential(u: np.ndarray, v: np.ndarray, n: int) -> tuple[float, int]:
    """(best density, its number of vertices); ties by the least vertex. Least degrees are kept by blocks of vertices, so
    that nothing is held but the edges."""
    starts, near = neighbours([(u, v), (v, u)], n)
    begin, block = starts.tolist(), max(64, math.isqrt(n))
    deg = np.full(-(-n // block) * block, GONE)
    deg[:n] = np.diff(starts)
    blocks = deg.reshape(-1, block)
    low = blocks.min(axis=1)
    edges, left = len(u), n
    best, size = edges / max(1, n), n
    while left > 1:
        b = int(low.argmin())
        i = b * block + int(blocks[b].argmin())
        left -= 1
        edges -= int(deg[i])
        deg[i] = GONE
        ends = near[begin[i] : begin[i + 1]]
        np.subtract.at(deg, ends, 1)
        np.minimum.at(low, ends // block, deg[ends])
        low[b] = blocks[b].min()
        if edges / left > best:
            best, size = edges / left, left
    return best, size


def peel_batched(edges: DataFrame, eps: float = 0.1, most: int = 200) -> tuple[float, list[tuple[int, int, int]]]:
    """(best density, per pass: number, vertices and edges left before it). A pass drops every vertex whose degree is
    at most 2 (1 + eps) times the density, a constant share of the vertices."""
    now, best, passes = edges.select("u", "v"), 0.0, []
    for k in range(most):
        deg = materialise(now.select(F.explode(F.array("u", "v")).alias("vid")).groupBy("vid").agg(F.count(F.lit(1)).alias("degree")), "degrees")
        n, twice = deg.agg(F.count(F.lit(1)), F.sum("degree")).first()
        if not n:
            break
        density = twice / 2 / n
        best = max(best, density)
        passes.append((k, n, twice // 2))
        stay = deg.where(F.col("degree") > 2 * (1 + eps) * density).select("vid")
        now = now.join(stay.withColumnRenamed("vid", "u"), "u", "left_semi").join(stay.withColumnRenamed("vid", "v"), "v", "left_semi")
        now = materialise(now, "peeled")
    return best, passes
