"""SQL entry points: a table function that solves one graph per partition, and reporting functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from poslp.config import SolveConfig

LOCAL = "problem string, n_vertices long, n_edges long, status string, objective double, lower double, upper double, iters long"


def _solve(pairs: np.ndarray, problem: str, eps: float) -> tuple:
    from poslp.plans.problems import index_edges, solve_local

    u, v, ids = index_edges(pairs)
    o = solve_local(problem, u, v, len(ids), SolveConfig(eps=eps))
    return problem, len(ids), len(u), str(o.status), float(o.best), float(o.lower), float(o.upper), int(o.iters)


@udtf(returnType="graph_id long, " + LOCAL)
class SolveGraph:
    """SELECT * FROM solve_graph(TABLE(edges) PARTITION BY (graph_id), 'matching', 0.1): edges (graph_id, u, v)."""

    def __init__(self):
        self.pairs, self.args = [], None

    def eval(self, row, problem: str, eps: float):
        self.pairs.append((row["u"], row["v"]))
        self.args = (row["graph_id"], problem, float(eps))

    def terminate(self):
        if self.args:
            graph, problem, eps = self.args
            yield (graph, *_solve(np.array(self.pairs), problem, eps))


def solve_components(edges: DataFrame, problem: str, eps: float = 0.1) -> DataFrame:
    """One row per component; edges: (component, u, v), each component of a size that a task can hold."""

    def run(component: pa.Table) -> pa.Table:
        pairs = np.stack([component.column("u").to_numpy(), component.column("v").to_numpy()], axis=1)
        row = (component.column("component")[0].as_py(), *_solve(pairs, problem, eps))
        names = ["component", *(c.split()[0] for c in LOCAL.split(", "))]
        return pa.table({n: [x] for n, x in zip(names, row)})

    return edges.groupBy("component").applyInArrow(run, "component long, " + LOCAL)


def log_sum_exp_udaf(eta: float):
    """A grouped aggregate on Arrow batches, for use in SQL; smooth.log_sum_exp combines on the map side and is the one
    to use on large columns."""
    import pandas as pd

    @F.pandas_udf("double")
    def log_sum_exp(v: pd.Series) -> float:
        x = eta * v.to_numpy()
        return float(x.max() + np.log(np.exp(x - x.max()).sum()))

    return log_sum_exp


def register(spark: SparkSession) -> None:
    spark.udtf.register("solve_graph", SolveGraph)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION max_violation(max_px DOUBLE, min_cx DOUBLE) RETURNS DOUBLE RETURN greatest(0, max_px - 1, 1 - min_cx)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION relative_error(value DOUBLE, best DOUBLE) RETURNS DOUBLE RETURN abs(value - best) / best")
