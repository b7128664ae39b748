"""Accuracy and cost measures."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

LIMIT = 4 * 3600.0


def max_violation(max_px: float, min_cx: float) -> float:
    return max(0.0, max_px - 1, 1 - min_cx)


def is_eps_feasible(max_px: float, min_cx: float, eps: float) -> bool:
    return max_px <= 1 + eps and min_cx >= 1 - 1e-12


def relative_error(value: float, best: float, sense: str) -> float:
    return 1 - value / best if sense == "max" else value / best - 1


def timed(run: Callable, limit: float = LIMIT) -> tuple[float | None, object]:
    """(seconds, result); no seconds where the run failed or went over the limit."""
    begun = time.perf_counter()
    try:
        out = run()
    except Exception as e:  # a failed run is a dash in the table, and the reason its result
        return None, e
    took = time.perf_counter() - begun
    return (took if took <= limit else None), out


def speedup(base: float | None, ours: float | None) -> float | None:
    return base / ours if base and ours else None


def geomean(df: DataFrame, col: str) -> float:
    return df.where(F.col(col) > 0).agg(F.exp(F.avg(F.log(col)))).first()[0]


def share_above(df: DataFrame, col: str, least: float) -> float:
    return df.agg(F.avg((F.col(col) > least).cast("double"))).first()[0]


def time_shares(trace: list[dict]) -> dict[str, float]:
    parts = {k: sum(t[f"t_{k}"] for t in trace) for k in ("matvec", "vec", "search")}
    whole = sum(parts.values()) or 1.0
    return {k: v / whole for k, v in parts.items()}


def check_invariants(trace: list[dict], slack: float = 1e-9) -> bool:
    """Accepted steps never raise the potential."""
    return all(t["potential"] <= t["potential_before"] + slack for t in trace)


def shuffle_words(n: int, m: int, p: int, layout: str) -> float:
    """Words moved per product: by edges twice each, by a square grid of p blocks 2 sqrt(p) copies of the vertices, by
    rows of blocks one copy of what each block needs."""
    if layout == "naive":
        return 4.0 * m
    if layout == "grid2d":
        return 2.0 * math.sqrt(p) * n
    if layout == "row1d":
        return float(min(n * p, 2 * m))
    raise ValueError(layout)


def comm_ratio(compute_s: float, fetch_s: float) -> float:
    return compute_s / fetch_s if fetch_s else math.inf


def stored_entries(op) -> int:
    """Numbers kept for an operator: two per column of an implicit incidence, three per explicit entry."""
    return 2 * op.shape[1] if type(op).__name__ == "Incidence" else 3 * op.nnz


def total_work(outcome, entries: int) -> int:
    """Matrix entries touched by a solve: each iteration multiplies by both matrices and their transposes once; trial steps
    touch none."""
    return 4 * entries * outcome.iters


def shuffled_bytes(spark: SparkSession, settle: float = 0.3) -> int:
    """Written to shuffles by this application so far. Counters arrive with a delay, for which it waits."""
    time.sleep(settle)
    held = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    return sum(held.apply(i).totalShuffleWrite() for i in range(held.size()))
