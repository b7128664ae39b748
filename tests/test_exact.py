from fractions import Fraction

import numpy as np
import pytest

from poslp.baselines.exact import brute_force, max_flow_density
from poslp.baselines.gradient import coordinate_step
from poslp.baselines.matching import double_cover_value
from poslp.baselines.peel import peel_sequential
from poslp.config import SolveConfig, Status
from poslp.plans.problems import solve, solve_local
from poslp.sources import sinks, synth
from poslp.sources.graphs import GRAPHS
from poslp import workloads
from poslp.operators.knn import block_knn
from poslp.queries_steps import _crossing
from poslp.registry import queries
from poslp.workloads import backoff_ablation, coordinate_search, four_problems, local_graph


def _graph(rng, n, p):
    u, v = np.triu_indices(n, 1)
    keep = rng.random(len(u)) < p
    keep[0] = True
    return u[keep], v[keep], n


@pytest.mark.parametrize("seed", range(8))
def test_relaxations_against_integer_optima(seed):
    rng = np.random.default_rng(seed)
    u, v, n = _graph(rng, 6, 0.5)
    fractional = double_cover_value(u, v, n)
    assert brute_force("matching", u, v, n)[0] <= fractional <= brute_force("vcover", u, v, n)[0]
    assert brute_force("matching", u, v, n)[0] >= 2 / 3 * fractional - 1e-9
    dense = max_flow_density(u, v, n)
    assert float(dense[0]) == pytest.approx(brute_force("densest", u, v, n)[0])
    linked = np.unique(np.r_[u, v])
    if len(linked) == n:
        o = solve_local("domset", u, v, n, SolveConfig(step="newton"))
        assert o.lower <= brute_force("domset", u, v, n)[0] + 1e-9
        o = solve_local("densest", u, v, n, SolveConfig(step="newton"))
        assert o.lower <= float(dense[0]) * (1 + 1e-9) and o.upper >= float(dense[0]) * (1 - 1e-9)


@pytest.mark.parametrize("seed", range(4))
def test_flow_bounds_peeling(seed):
    u, v, n = _graph(np.random.default_rng(seed), 40, 0.15)
    best, members = max_flow_density(u, v, n)
    held = np.isin(np.arange(n), members)
    assert best == Fraction(int((held[u] & held[v]).sum()), len(members))
    assert peel_sequential(u, v, n)[0] <= float(best) <= 2 * peel_sequential(u, v, n)[0]


def test_enumeration_is_bounded():
    with pytest.raises(ValueError):
        brute_force("vcover", np.array([0]), np.array([1]), 21)


def test_workload_tables(spark, data):
    rows = four_problems(spark, data).collect()
    for r in rows:
        good = r["value"] >= r["integer_optimum"] * 0.97 if r["problem"] == "matching" else r["value"] <= r["integer_optimum"] * 1.03
        assert good, r
    coordinate = {(r["size"], r["method"]): r for r in coordinate_search(spark, data).collect()}
    assert all(r["status"] == Status.FEASIBLE for r in coordinate.values())
    assert coordinate[32, "whole direction"]["dependent_steps"] < coordinate[32, "coordinates, fixed step"]["dependent_steps"]
    assert all(r["lower"] <= r["upper"] * (1 + 1e-9) for r in backoff_ablation(spark, data, 5).collect())


def test_trace_sink_replaces_its_own_run(spark, tmp_path):
    one = spark.createDataFrame([(0, 1.0), (1, 0.5)], "iter long, max_violation double")
    for _ in range(2):
        sinks.append_trace(one, str(tmp_path / "t"), "a", "g", "matching")
    sinks.append_trace(one, str(tmp_path / "t"), "b", "g", "matching")
    assert spark.read.parquet(str(tmp_path / "t")).groupBy("run").count().orderBy("run").collect() == [("a", 2), ("b", 2)]
    sinks.write_report(one, str(tmp_path / "r"))
    assert spark.read.option("header", True).csv(str(tmp_path / "r")).count() == 2


def test_bucketed_join_has_no_exchange(spark, data):
    from poslp.queries_tools import sink_bucketed_join

    assert "Exchange" not in sink_bucketed_join(spark, data)._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("step", ["newton", "binary"])
def test_a_bracket_that_degrees_close_still_gets_a_point(spark, step):
    """On a lattice the degrees alone bound the matching to within 1 + eps, before any point is known."""
    u, v, ids = local_graph(synth.grid(spark, 24, 24))
    o = solve_local("matching", u, v, len(ids), SolveConfig(step=step, max_iter=400))
    exact = double_cover_value(u, v, len(ids))
    assert o.status == Status.FEASIBLE and o.best >= exact / 1.1 * (1 - 1e-9) and o.lower <= exact * (1 + 1e-9) <= o.upper * (1 + 2e-9)


def test_large_graphs_come_in_slices(spark, monkeypatch):
    monkeypatch.setattr(workloads, "SLICE", 100)
    u, v, ids = local_graph(synth.grid(spark, 24, 24))
    assert len(u) > 900 and len(ids) == 576 and (np.lexsort((v, u)) == np.arange(len(u))).all()
    assert not hasattr(workloads, "LOCAL_EDGES")


@pytest.mark.parametrize("name", ["four_problems", "backoff_ablation", "coordinate_search", "integer_programs"])
def test_measured_tables_read_a_given_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        queries()[name](spark, str(tmp_path)).collect()


def test_neighbours_across_blocks(spark, data):
    rows = spark.read.parquet(f"{data}/embeddings.parquet")
    got = {(r["a"], r["b"]) for r in block_knn(rows, "vec_id", "embedding", 8, side=100).collect()}
    held = rows.orderBy("vec_id").toPandas()
    x = np.stack(held.embedding.to_numpy()).astype(float)
    x /= np.linalg.norm(x, axis=1)[:, None]
    s = x @ x.T
    np.fill_diagonal(s, -2)
    ids = held.vec_id.to_numpy()
    near = np.argsort(-s, axis=1, kind="stable")[:, :8]
    want = {(int(ids[i]), int(ids[j])) for i in range(len(ids)) for j in near[i]}
    assert len(got) == 8 * len(ids) and len(got ^ want) <= len(ids) // 50  # ties of copies


@pytest.mark.parametrize("at", [2.0**3 + 1, 2.0**24, 48_938_374.7, 2.0**50])
def test_the_crossing_is_bracketed_however_large(at):
    from types import SimpleNamespace

    lo, hi = _crossing(lambda alphas: [SimpleNamespace(alpha=a, accepted=a <= at) for a in alphas])
    assert lo <= at < hi and hi - lo <= lo / 256


def test_a_split_by_degrees_closes_stars(spark):
    """Stars of 3 and 9 leaves: no iteration is needed, and the point splits every edge within the density."""
    leaves = [(0, k) for k in range(1, 10)] + [(100, k) for k in range(101, 104)]
    o = solve("densest", spark.createDataFrame(leaves, "u long, v long"), SolveConfig())
    x = {r["var"]: r["x"] for r in o.values().collect()}
    assert o.outcome.status == Status.FEASIBLE and o.outcome.iters == 0
    assert o.outcome.lower == pytest.approx(0.9) and o.outcome.upper == pytest.approx(0.9)
    assert all(x[2 * k] + x[2 * k + 1] == pytest.approx(1) for k in range(12)) and sum(x[2 * k] for k in range(9)) <= 0.9 + 1e-9


@pytest.mark.parametrize("odd_centre", [True, False])
def test_the_smaller_side_is_the_cover_where_degrees_close_the_bracket(spark, odd_centre):
    edges = [(2 * k + 2, 1) if odd_centre else (2 * k + 1, 0) for k in range(6)]
    o = solve("vcover", spark.createDataFrame([tuple(sorted(e)) for e in edges], "u long, v long"), SolveConfig())
    x = {r["var"]: r["x"] for r in o.values().collect()}
    assert o.outcome.iters == 0 and o.outcome.best == 1 and o.outcome.lower == pytest.approx(1)
    assert all(x[a] + x[b] >= 1 for a, b in edges) and sum(x.values()) == 1


def test_each_violation_curve_is_a_task_of_its_own(spark, data, monkeypatch):
    """The methods run in Spark's tasks, where this change to the driver's module is not seen, with the curves of one process."""
    u, v, ids = local_graph(GRAPHS["user_eventtype"](spark, data))
    want = {m: workloads._curve(m, u, v, ids % 2 == 0, 0.05, 30) for m in workloads.METHODS}
    monkeypatch.setattr(workloads, "solve_generalized", None)
    rows = workloads.violation_curves(spark, data, most=30, graphs=("user_eventtype",)).orderBy("method", "iter").collect()
    assert {m: [(r["iter"], r["max_violation"]) for r in rows if r["method"] == m] for m in workloads.METHODS} == want
