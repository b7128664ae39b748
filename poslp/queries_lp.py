"""General positive programs from tables, with right sides and costs, against their closed forms.

Nations are variables, regions rows: each region's part is a program with one row, whose optimum takes its best nation.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from poslp.config import SolveConfig
from poslp.plans import lp
from poslp.queries import EPS, query
from poslp.sources.graphs import table

_W, _C, _B = "(1 + n_nationkey % 3)", "(1 + n_nationkey % 5)", "(2 + n_regionkey)"
REPORT = "problem string, optimum double, feasible boolean, within_eps boolean, bracket_holds boolean"


def _sql(problem: str, best: str) -> str:
    return f"SELECT '{problem}' AS problem, round(sum(best), 6) AS optimum, true AS feasible, true AS within_eps, true AS bracket_holds FROM (SELECT {best}({_C} * {_B} / {_W}::DOUBLE) AS best FROM nation GROUP BY n_regionkey)"


def _tables(spark, d):
    n = table(spark, d, "nation")
    a = n.select(F.col("n_regionkey").alias("row"), F.col("n_nationkey").alias("var"), F.expr(_W).alias("val"))
    bound = n.select(F.col("n_regionkey").alias("row"), F.expr(_B).alias("bound")).distinct()
    return n, a, bound, n.select(F.col("n_nationkey").alias("var"), F.expr(_C).alias("cost"))


def _best(n, how) -> float:
    return n.groupBy("n_regionkey").agg(how(F.expr(f"{_C} * {_B} / {_W}")).alias("b")).agg(F.sum("b")).first()[0]


def _row(spark, problem: str, o, best: float, feasible: bool, most: bool):
    near = o.best >= best / (1 + EPS) - 1e-9 if most else o.best <= best * (1 + EPS) + 1e-9
    return spark.createDataFrame([(problem, round(best, 6), feasible, bool(near), bool(o.lower <= best * (1 + 1e-9) and o.upper >= best * (1 - 1e-9)))], REPORT)


def _loads(a, bound, x):
    return a.join(x, "var").groupBy("row").agg(F.sum(F.col("val") * F.col("x")).alias("s")).join(bound, "row").select(F.col("s") / F.col("bound"))


@query("lp_packing_weighted", _sql("packing", "max"))
def lp_packing_weighted(spark, d):
    n, a, bound, cost = _tables(spark, d)
    program = lp.standardise(a, None, packing_bound=bound, cost=cost)
    o = lp.solve_packing(program, SolveConfig(eps=EPS))
    return _row(spark, "packing", o, _best(n, F.max), all(r[0] <= 1 + 1e-9 for r in _loads(a, bound, lp.values(program, o)).collect()), True)


@query("lp_covering_weighted", _sql("covering", "min"))
def lp_covering_weighted(spark, d):
    n, a, bound, cost = _tables(spark, d)
    program = lp.standardise(None, a, covering_bound=bound, cost=cost)
    o = lp.solve_covering(program, SolveConfig(eps=EPS))
    return _row(spark, "covering", o, _best(n, F.min), all(r[0] >= 1 - 1e-9 for r in _loads(a, bound, lp.values(program, o)).collect()), False)
