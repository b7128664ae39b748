"""General positive linear programs from tables: entries (row, var, val), right sides and costs by key.

``standardise`` divides rows by their right sides and columns by their costs, and settles what those leave open: a packing
row of bound zero fixes its variables at zero, a covering row of bound zero asks nothing, a variable of cost zero satisfies
its covering rows for nothing or adds nothing to a packing objective. What remains has all right sides and costs one; its
entries stay in Spark, as blocks where row and column vectors are of a checked size, else as frames.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poslp.config import SolveConfig, Status
from poslp.operators.frames import CooFrames
from poslp.operators.matrices import ObjectiveRow, Stack
from poslp.plans.blocks import ColumnBackend, EntryProduct
from poslp.plans.distributed import Side, SparkBackend
from poslp.plans.shared import materialise
from poslp.plans.solver import Outcome, search_target, solve_feasibility

ENTRIES = "row long, var long, val double"


@dataclass
class PositiveLp:
    """Standard form. packing, covering: entries, or None; variables: (var, cost, top), x = x' / cost; free: variables that
    cost nothing and may be as large as they like; infeasible, unbounded: what the tables alone prove."""

    packing: DataFrame | None
    covering: DataFrame | None
    variables: DataFrame
    free: DataFrame | None = None
    infeasible: bool = False
    unbounded: bool = False


def entries(df: DataFrame) -> DataFrame:
    """(row, var, val) with repeated places added and zeros left out; negative values are refused."""
    df = df.select(F.col("row").cast("long").alias("row"), F.col("var").cast("long").alias("var"), F.col("val").cast("double").alias("val")).where(F.col("val") != 0)
    if df.where(F.col("val") < 0).limit(1).count():
        raise ValueError("entries must not be negative")
    return df.groupBy("row", "var").agg(F.sum("val").alias("val"))


def _sided(a: DataFrame, bound: DataFrame | None) -> DataFrame:
    """a with the row's bound, one where none is given."""
    if bound is None:
        return a.withColumn("bound", F.lit(1.0))
    b = bound.select(F.col("row").cast("long").alias("row"), F.col("bound").cast("double").alias("bound"))
    return a.join(b, "row", "left").fillna(1.0, ["bound"])


def standardise(packing: DataFrame | None, covering: DataFrame | None, packing_bound: DataFrame | None = None, covering_bound: DataFrame | None = None, cost: DataFrame | None = None) -> PositiveLp:
    """packing_bound, covering_bound: (row, bound); cost: (var, cost); ones where not given. A covering row with a positive
    bound and no entry, or whose variables are all fixed at zero, makes the program infeasible."""
    p = None if packing is None else materialise(_sided(entries(packing), packing_bound), "packing")
    c = None if covering is None else materialise(_sided(entries(covering), covering_bound).where(F.col("bound") > 0), "covering")
    asked = None if c is None else c.select("row").distinct()
    if covering_bound is not None and asked is not None:
        asked = covering_bound.where(F.col("bound") > 0).select(F.col("row").cast("long").alias("row")).unionByName(asked).distinct()
    if p is not None:
        zero = p.where(F.col("bound") == 0).select("var").distinct()
        p = p.where(F.col("bound") > 0).join(zero, "var", "left_anti")
        c = None if c is None else c.join(zero, "var", "left_anti")
    every = [f.select("var") for f in (p, c) if f is not None]
    names = every[0] if len(every) == 1 else every[0].unionByName(every[1])
    costs = names.distinct().withColumn("cost", F.lit(1.0))
    if cost is not None:
        given = cost.select(F.col("var").cast("long").alias("var"), F.col("cost").cast("double").alias("_c"))
        costs = costs.join(given, "var", "left").select("var", F.coalesce("_c", "cost").alias("cost"))
    costs = materialise(costs, "costs")
    # without a packing side, what costs nothing satisfies its rows
    free = None
    if p is None:
        free = materialise(costs.where(F.col("cost") == 0).select("var"), "free")
        done = c.join(free, "var", "left_semi").select("row").distinct()
        c, asked = c.join(done, "row", "left_anti"), asked.join(done, "row", "left_anti")
    costs = costs.where(F.col("cost") > 0)
    scale = lambda f: None if f is None else materialise(f.join(costs, "var").select("row", "var", (F.col("val") / F.col("bound") / F.col("cost")).alias("val")), "scaled")
    p, c = scale(p), scale(c)
    infeasible = c is not None and bool(asked.join(c.select("row").distinct(), "row", "left_anti").limit(1).count())
    # a variable that no packing row holds back
    loose = p is not None and bool(costs.join(p.select("var").distinct(), "var", "left_anti").limit(1).count())
    tops = (p if p is not None else c).groupBy("var").agg(F.max("val").alias("top"))
    variables = materialise(costs.join(tops, "var"), "variables")
    return PositiveLp(p, c, variables, free, infeasible, loose)


def _keys(df: DataFrame, col: str) -> np.ndarray:
    return df.select(col).distinct().orderBy(col).toArrow().column(col).to_numpy()


def _maker(lp: PositiveLp, cfg: SolveConfig):
    """make(target) of a backend for one side and the objective row, or make() for both: vectors on the driver where rows and
    columns are of a checked size, else frames."""
    sides = {k: f for k, f in (("p", lp.packing), ("c", lp.covering)) if f is not None}
    size = 8 * max(lp.variables.count(), *(f.select("row").distinct().count() for f in sides.values()))
    if cfg.layout == "blocks" or cfg.layout == "auto" and size <= cfg.vertex_bytes:
        columns = _keys(lp.variables, "var")
        held = {k: EntryProduct(f, _keys(f, "row"), columns) for k, f in sides.items()}

        def make(target: float | None = None):
            goal = ObjectiveRow(len(columns), target) if target else None
            p, c = held.get("p", goal), held.get("c", goal)
            return ColumnBackend(p, Stack(c, goal) if target and len(held) == 2 else c, columns)

        return make

    def frames(target: float | None = None):
        c = lp.covering
        if target and len(sides) == 2:
            c = materialise(c.unionByName(lp.variables.select(F.lit(-1).cast("long").alias("row"), "var", F.lit(1.0 / target).alias("val"))), "with-goal")
        side = lambda a: Side(target=target) if a is None else Side(CooFrames(a), a.select("row").distinct())
        return SparkBackend(lp.variables, side(lp.packing), side(c), "top" if lp.packing is not None else 1.0 / target, cfg.checkpoint_every)

    return frames


def _searched(lp: PositiveLp, cfg: SolveConfig, lo: float, hi: float, kind: str, point: Outcome | None = None) -> Outcome:
    make = _maker(lp, cfg)
    return search_target(lambda t, en, e: solve_feasibility(make(t), replace(cfg, eps=e), kind, en), lo, hi, cfg.eps, kind, lanes=cfg.target_lanes, point=point)


def solve_mixed(lp: PositiveLp, cfg: SolveConfig) -> Outcome:
    """Px <= 1, Cx >= 1."""
    return Outcome(Status.INFEASIBLE_DIRECTION, 0, []) if lp.infeasible else solve_feasibility(_maker(lp, cfg)(), cfg, "mixed")


def solve_packing(lp: PositiveLp, cfg: SolveConfig) -> Outcome:
    """max sum(x), Px <= 1. Each variable alone reaches 1 / its largest entry; together at most the sum of those."""
    if lp.unbounded:
        return Outcome(Status.ITER_LIMIT, 0, [], math.inf, math.inf, math.inf)
    lo, hi = lp.variables.agg(F.max(1 / F.col("top")), F.sum(1 / F.col("top"))).first()
    return Outcome(Status.FEASIBLE, 0, [], 0.0, 0.0, 0.0) if lo is None else _searched(lp, cfg, lo, hi, "packing")


def solve_covering(lp: PositiveLp, cfg: SolveConfig) -> Outcome:
    """min sum(x), Cx >= 1. The hardest row asks 1 / its largest entry; serving each row by its best variable is enough."""
    if lp.infeasible:
        return Outcome(Status.INFEASIBLE_DIRECTION, 0, [], math.inf, math.inf, math.inf)
    each = lp.covering.groupBy("row").agg((1 / F.max("val")).alias("need"), F.max_by("var", F.struct("val", "var")).alias("var"))
    lo, hi = each.agg(F.max("need"), F.sum("need")).first()
    if lo is None:
        return Outcome(Status.FEASIBLE, 0, [], 0.0, 0.0, 0.0)
    served = materialise(each.groupBy("var").agg(F.sum("need").alias("x")), "served")
    return _searched(lp, cfg, lo, hi, "covering", Outcome(Status.FEASIBLE, 0, [], lo, hi, hi, served, 1.0, 0.0))


def solve_mixed_optimum(lp: PositiveLp, cfg: SolveConfig, most: int = 30) -> Outcome:
    """max sum(x), Px <= 1, Cx >= 1: the objective over a target is one more covering row. A feasible target is a lower
    bound (up to the accuracy); no direction left proves that the target is beyond the optimum."""
    if lp.infeasible:
        return Outcome(Status.INFEASIBLE_DIRECTION, 0, [])
    make = _maker(lp, cfg)
    best = solve_feasibility(make(), cfg, "mixed")
    if best.status != Status.FEASIBLE:
        return best
    value = lambda o: float(_frame(o).agg(F.sum("x")).first()[0]) * o.scale / (1 + 1.2 * cfg.eps)
    lower, upper, iters, inner = value(best), lp.variables.agg(F.sum(1 / F.col("top"))).first()[0], best.iters, cfg.eps
    for _ in range(most):
        if upper <= (1 + cfg.eps) * lower:
            break
        target = math.sqrt(lower * upper)
        o = solve_feasibility(make(target), replace(cfg, eps=inner), "mixed")
        iters += o.iters
        if o.status == Status.FEASIBLE:
            was, lower = lower, max(lower, value(o))
            best = o if lower > was else best
        if o.status == Status.INFEASIBLE_DIRECTION:
            upper = target
        elif lower < target / (1 + inner / 4):
            inner /= 2
            if inner < cfg.eps / 16:
                break
    out = replace(best)
    out.status = Status.FEASIBLE if upper <= (1 + cfg.eps) ** 2 * lower else Status.ITER_LIMIT
    out.iters, out.lower, out.upper, out.best = iters, lower, upper, lower
    return out


def _frame(outcome: Outcome) -> DataFrame:
    return outcome.x.frame() if hasattr(outcome.x, "frame") else outcome.x


def values(lp: PositiveLp, outcome: Outcome) -> DataFrame:
    """(var, x) in the units of the tables given."""
    x = _frame(outcome).select("var", (F.col("x") * F.lit(float(outcome.scale))).alias("_x"))
    return x.join(lp.variables.select("var", "cost"), "var").select("var", (F.col("_x") / F.col("cost")).alias("x"))
