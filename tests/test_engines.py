"""The engines against each other, exact values and the edge cases of inputs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from poslp.baselines.linear import packing_value, simplex
from poslp.baselines.matching import double_cover_value
from poslp.config import SolveConfig, Status
from poslp.operators.matrices import Coo, Incidence, ObjectiveRow
from poslp.plans import lp
from poslp.plans.problems import components, local_bracket, solve, solve_local, two_colourable
from poslp.plans.solver import LocalBackend, solve_feasibility
from poslp.sources import synth
from poslp.sources.graphs import canonical


@pytest.fixture(scope="module")
def graph(spark):
    more = spark.createDataFrame([(0, 4), (2, 7), (100, 3), (100, 200)], "u long, v long")
    return canonical(synth.cycle(spark, 9).unionByName(more)).cache()


@pytest.mark.parametrize("problem", ["matching", "vcover", "domset", "densest"])
def test_engines_agree_on_bounds_and_ids(spark, graph, problem):
    a, b = (solve(problem, graph, SolveConfig(engine=e, eps=0.2)) for e in ("local", "spark"))
    assert a.outcome.status == b.outcome.status == Status.FEASIBLE
    assert a.outcome.lower <= b.outcome.upper * (1 + 1e-9) and b.outcome.lower <= a.outcome.upper * (1 + 1e-9)
    x, y = (s.values().orderBy("var").toPandas() for s in (a, b))
    assert x["var"].tolist() == y["var"].tolist()
    if problem in ("vcover", "domset"):
        assert set(y["var"]) == {*range(9), 100, 200}
        held = dict(zip(y["var"], y["x"]))
        rows = graph.collect()
        if problem == "vcover":
            assert all(held[r["u"]] + held[r["v"]] >= 1 - 1e-9 for r in rows)


def test_frames_agree_with_blocks(spark):
    star = synth.star(spark, 4)
    for kw in ({"layout": "frames"}, {"layout": "blocks"}, {"layout": "blocks", "drop_satisfied": True}, {"layout": "frames", "drop_satisfied": True}):
        o = solve("vcover", star, SolveConfig(eps=0.3, **kw)).outcome
        assert o.status == Status.FEASIBLE and o.lower <= 1 + 1e-9 and o.upper >= 1 - 1e-9


@pytest.mark.parametrize("step", ["exponential", "binary", "kary", "newton", "first_order"])
def test_no_feasible_target_is_called_infeasible(step):
    rng = np.random.default_rng(5)
    for _ in range(8):
        n = int(rng.integers(4, 12))
        i, j = np.triu_indices(n, 1)
        pick = rng.random(len(i)) < 0.5
        u, v = i[pick], j[pick]
        if not len(u):
            continue
        ids, flat = np.unique(np.r_[u, v], return_inverse=True)
        u, v, n = flat[: len(u)], flat[len(u) :], len(ids)
        best = double_cover_value(u, v, n)
        for share in (0.9, 0.97, 1.0):
            o = solve_feasibility(LocalBackend(Incidence(u, v, n), ObjectiveRow(len(u), share * best)), SolveConfig(step=step, max_iter=300), "packing")
            assert o.status not in (Status.INFEASIBLE_STEP, Status.INFEASIBLE_DIRECTION) or share == 1.0 and o.upper >= best * (1 - 1e-9)
            assert o.lower <= best * (1 + 1e-9) and o.upper >= best * (1 - 1e-9)
        o = solve_feasibility(LocalBackend(Incidence(u, v, n), ObjectiveRow(len(u), 1.3 * best)), SolveConfig(step=step, max_iter=300), "packing")
        # steps that slopes alone allow may creep to the limit
        assert o.status in (Status.INFEASIBLE_STEP, Status.INFEASIBLE_DIRECTION) or step == "first_order" and o.status == Status.ITER_LIMIT
        assert o.upper >= best * (1 - 1e-9)
        b = local_bracket(u, v, n)
        assert b.of("matching", "tight")[0] <= best * (1 + 1e-9) <= b.of("matching", "tight")[1] * (1 + 2e-9)


@pytest.mark.parametrize("kw", [{"target_lanes": 3}, {"warm_targets": True}, {"backoff": 0.25, "step": "newton"}, {"bound": "paper"}])
def test_search_variants_close_the_same_bracket(kw):
    u, v, n = np.arange(9), (np.arange(9) + 1) % 9, 9
    o = solve_local("matching", u, v, n, SolveConfig(**kw))
    assert o.status == Status.FEASIBLE and o.lower <= 4.5 * (1 + 1e-9) and o.upper >= 4.5 * (1 - 1e-9)


def test_general_programs(spark):
    rng = np.random.default_rng(2)
    a, b, c = rng.integers(0, 4, (4, 5)), rng.integers(1, 5, 4), rng.integers(1, 4, 5)
    a[0] = 1
    rows = [(i, j, float(a[i, j])) for i in range(4) for j in range(5) if a[i, j]]
    entries = spark.createDataFrame(rows, "row long, var long, val double")
    bound = spark.createDataFrame([(i, float(x)) for i, x in enumerate(b)], "row long, bound double")
    cost = spark.createDataFrame([(j, float(x)) for j, x in enumerate(c)], "var long, cost double")
    best = simplex(a.astype(float), b.astype(float), c.astype(float))[0]
    program = lp.standardise(entries, None, packing_bound=bound, cost=cost)
    o = lp.solve_packing(program, SolveConfig(eps=0.3))
    assert o.status == Status.FEASIBLE and o.lower <= best * (1 + 1e-9) and o.upper >= best * (1 - 1e-9)
    x = {r["var"]: r["x"] for r in lp.values(program, o).collect()}
    assert all(sum(a[i, j] * x.get(j, 0) for j in range(5)) <= b[i] + 1e-6 for i in range(4))
    assert sum(c[j] * x.get(j, 0) for j in range(5)) == pytest.approx(o.best, rel=1e-6)


def test_standard_form_settles_zero_sides(spark):
    a = spark.createDataFrame([(0, 0, 1.0), (0, 1, 1.0), (1, 1, 2.0), (1, 1, 2.0)], "row long, var long, val double")
    zero = spark.createDataFrame([(0, 0.0)], "row long, bound double")
    p = lp.standardise(a, a, packing_bound=zero)
    assert p.infeasible  # both variables stand in a packing row of bound zero
    c = lp.standardise(None, a, covering_bound=zero)
    assert [tuple(r) for r in c.covering.collect()] == [(1, 1, 4.0)]
    free = lp.standardise(None, a, cost=spark.createDataFrame([(1, 0.0)], "var long, cost double"))
    assert lp.solve_covering(free, SolveConfig()).best == 0.0 and free.free.count() == 1
    loose = lp.standardise(spark.createDataFrame([(0, 0, 1.0)], a.schema), spark.createDataFrame([(0, 5, 1.0)], a.schema))
    assert loose.unbounded
    with pytest.raises(ValueError):
        lp.standardise(spark.createDataFrame([(0, 0, -1.0)], a.schema), None)


def test_components_of_a_long_path_and_odd_cycles(spark):
    path = synth.path(spark, 400)
    assert components(path.withColumnsRenamed({"u": "a", "v": "b"})).select("component").distinct().count() == 1
    assert two_colourable(path) and not two_colourable(synth.cycle(spark, 7)) and two_colourable(synth.cycle(spark, 8).select((2 * F.col("u")).alias("u"), (2 * F.col("v")).alias("v")))


def test_edge_files_keep_every_entry(spark, tmp_path):
    (tmp_path / "a.mtx").write_text("%%MatrixMarket matrix coordinate integer general\n% c\n3 3 2\n1 2 5\n2 3 7\n")
    (tmp_path / "b.mtx").write_text("%%MatrixMarket matrix coordinate pattern symmetric\n4 4 2\n1 2\n3 4\n")
    got = [sorted(tuple(r) for r in synth.from_edge_file(spark, str(tmp_path / f)).collect()) for f in ("a.mtx", "b.mtx")]
    assert got == [[(1, 2), (2, 3)], [(1, 2), (3, 4)]]


def test_written_states_are_deleted(spark, tmp_path):
    from poslp.plans import shared

    old = spark.conf.get("spark.checkpoint.dir", None)
    shared._own_dir, was = str(tmp_path), shared._own_dir
    try:
        if old is None:
            solve("densest", synth.cycle(spark, 5), SolveConfig(eps=0.2, max_iter=60))
            assert sum(p.name.startswith("edge-state") for p in (tmp_path / "poslp").iterdir()) <= 2
    finally:
        shared._own_dir = was
