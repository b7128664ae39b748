import math

import numpy as np
import pytest

from poslp.baselines.gradient import coordinate_step, gradient_descent, phase_parallel, threshold_pure
from poslp.baselines.linear import concurrent, covering_value, dual_simplex, interior_point, packing_value, simplex
from poslp.baselines.matching import augmenting_matching, double_cover_value, greedy_matching, hopcroft_karp
from poslp.baselines.peel import peel_sequential
from poslp.config import SolveConfig, Status, eta
from poslp.functions.measures import check_invariants, relative_error
from poslp.operators.matrices import ClosedNeighbourhood, Coo, Incidence, ObjectiveRow, PairSum, PairToVertex, Stack, Tiled, Transposed
from poslp.plans.problems import generalized_matching_lp, index_edges, solve, solve_generalized, solve_local
from poslp.plans.solver import LocalBackend, solve_feasibility
from poslp.sources import synth
from poslp.sources.synth import random_binary

CYCLE = lambda n: (np.arange(n), (np.arange(n) + 1) % n, n)
COMPLETE = lambda n: (*np.triu_indices(n, 1), n)
STAR = lambda k: (np.zeros(k, dtype=int), np.arange(1, k + 1), k + 1)


@pytest.mark.parametrize("step", ["binary", "kary", "newton", "exponential"])
@pytest.mark.parametrize("graph,problem,best", [
    (CYCLE(9), "matching", 4.5), (CYCLE(9), "vcover", 4.5), (CYCLE(9), "domset", 3.0), (CYCLE(9), "densest", 1.0), (COMPLETE(12), "matching", 6.0), (COMPLETE(12), "domset", 1.0), (COMPLETE(12), "densest", 5.5),
    (STAR(6), "matching", 1.0), (STAR(6), "vcover", 1.0), (STAR(6), "domset", 1.0), (STAR(6), "densest", 6 / 7),
])
def test_closed_forms(graph, problem, best, step):
    o = solve_local(problem, *graph, SolveConfig(step=step))
    assert o.status == Status.FEASIBLE
    assert o.lower <= best * (1 + 1e-9) and o.upper >= best * (1 - 1e-9)
    assert o.upper <= 1.1 * o.lower * (1 + 1e-9)
    assert check_invariants(o.trace, 1e-7)


def test_path_of_two_edges_by_hand():
    op = Incidence(np.array([0, 0]), np.array([1, 2]), 3)
    b = LocalBackend(op, ObjectiveRow(2, 1.2))
    assert eta(b.rows, 0.1) == pytest.approx(138.629, abs=1e-3)
    b.start(0.1)
    s = b.stats(eta(4, 0.1))
    d = b.direction(eta(4, 0.1), s, 2.0)
    assert b.wp[0] == pytest.approx(0.998051, abs=1e-6) and d.min_g == pytest.approx(0.999025, abs=1e-6) and d.max_d == 0
    o = solve_feasibility(LocalBackend(op, ObjectiveRow(2, 0.5)), SolveConfig(step="exponential"), "packing")
    assert o.status == Status.FEASIBLE and o.iters == 1 and o.trace[0]["alpha"] == 2048


def test_search_needs_far_fewer_iterations_than_the_standard_step():
    u, v, n = CYCLE(11)
    make = lambda: LocalBackend(Incidence(u, v, n), ObjectiveRow(n, 5.4))
    quick = solve_feasibility(make(), SolveConfig(step="newton"), "mixed")
    slow = solve_feasibility(make(), SolveConfig(step="standard", max_iter=60_000), "mixed")
    assert quick.status == slow.status == Status.FEASIBLE and quick.iters * 50 < slow.iters
    assert slow.max_violation <= 0.12 and quick.max_violation <= 0.12


def test_ratio_falls_with_the_step_and_its_start_is_the_slope():
    u, v, n = COMPLETE(8)
    b = LocalBackend(Incidence(u, v, n), ObjectiveRow(len(u), 3.0))
    b.start(0.1)
    rate = eta(b.rows, 0.1)
    s = b.stats(rate)
    b.direction(rate, s, 2.0)
    ratios = [t.ratio for t in b.lanes(rate, s, [2.0**k for k in range(12)])]
    assert all(a >= c - 1e-6 for a, c in zip(ratios, ratios[1:]))


@pytest.mark.parametrize("drop", [False, True])
def test_dropping_rows_keeps_the_answer(drop):
    u, v, n = COMPLETE(10)
    o = solve_local("vcover", u, v, n, SolveConfig(drop_satisfied=drop, early_certificate=False))
    assert o.lower <= 5 * (1 + 1e-9) and o.upper >= 5 * (1 - 1e-9)


def test_infeasible_targets():
    u, v, n = COMPLETE(10)
    o = solve_feasibility(LocalBackend(Incidence(u, v, n), ObjectiveRow(len(u), 7.5)), SolveConfig(), "packing")
    assert o.status in (Status.INFEASIBLE_DIRECTION, Status.INFEASIBLE_STEP)
    lo, hi = np.full(n, 9.0), np.full(n, 2.0)
    assert solve_generalized(u, v, n, lo, hi, SolveConfig(eps=0.05)).status in (Status.INFEASIBLE_DIRECTION, Status.INFEASIBLE_STEP)


def test_operators_agree_with_their_entries():
    rng = np.random.default_rng(0)
    u, v, n = COMPLETE(9)
    for op in (Incidence(u, v, n), Transposed(Incidence(u, v, n)), ClosedNeighbourhood(u, v, n), PairSum(len(u)), PairToVertex(u, v, n, 2.5), Stack(Incidence(u, v, n), ObjectiveRow(len(u), 3.0))):
        x, w = rng.random(op.shape[1]), rng.random(op.shape[0])
        for other in (op.to_coo(), Tiled(op.to_coo(), 4)):
            assert np.allclose(op.apply(x), other.apply(x)) and np.allclose(op.apply_t(w), other.apply_t(w))
        assert w @ op.apply(x) == pytest.approx(op.apply_t(w) @ x)
        assert np.allclose(op.col_max(), op.to_coo().col_max())


def test_exact_solvers_agree():
    for seed in range(3):
        op = random_binary(14, 10, 0.3, seed)
        values = [packing_value(op, f) for f in (simplex, dual_simplex, interior_point, lambda *a: interior_point(*a, crossover=True))]
        assert np.allclose(values, values[0], atol=1e-6)
        assert covering_value(op) == pytest.approx(covering_value(op, interior_point), abs=1e-6)
    name, value, _ = concurrent(np.eye(3), np.ones(3), np.ones(3))
    assert name in ("simplex", "dual_simplex", "interior_point") and value == pytest.approx(3)


def test_random_binary_against_simplex():
    op = random_binary(60, 40, 0.2, 1)
    o = threshold_pure(op)
    best = packing_value(op)
    assert o.status == Status.FEASIBLE and o.lower <= best * (1 + 1e-9) and o.upper >= best * (1 - 1e-9)
    assert relative_error(o.best, best, "max") <= 0.1


def test_earlier_methods_solve_what_ours_solves():
    u, v, n = CYCLE(12)
    lo, hi = np.full(n, 0.5), np.full(n, 1.5)
    p, c = generalized_matching_lp(u, v, n, lo, hi)
    ours = solve_generalized(u, v, n, lo, hi, SolveConfig(eps=0.05, step="newton"))
    base = gradient_descent(p, c, 0.05)
    assert ours.status == base.status == Status.FEASIBLE and ours.iters < base.iters
    assert phase_parallel(p, c, 0.1).status == Status.FEASIBLE
    assert coordinate_step(p, c, 0.2).status == Status.FEASIBLE


def test_matchings_and_peeling(spark, data):
    from poslp.sources.graphs import customer_part

    edges = customer_part(spark, data).where("u % 5 = 0 or v % 7 = 0")
    pairs = np.array([(r["u"], r["v"]) for r in edges.collect()])
    u, v, ids = index_edges(pairs)
    exact = hopcroft_karp(u, v, len(ids), ids % 2 == 0)
    assert augmenting_matching(edges).count() == exact == double_cover_value(u, v, len(ids))
    assert exact / 2 <= greedy_matching(edges).count() <= exact
    assert peel_sequential(*COMPLETE(7))[0] == 3.0


def test_engines_agree(spark):
    edges = synth.cycle(spark, 7)
    for problem, best in (("matching", 3.5), ("vcover", 3.5)):
        o = solve(problem, edges, SolveConfig(engine="spark")).outcome
        assert o.status == Status.FEASIBLE and o.lower <= best * (1 + 1e-9) and o.upper >= best * (1 - 1e-9)
    with pytest.raises(ValueError):
        solve("bimatching", edges)


def test_empty_and_single(spark):
    none = spark.createDataFrame([], "u long, v long")
    assert solve("matching", none).report().first()["objective"] == 0
    one = solve("matching", spark.createDataFrame([(3, 8)], "u long, v long"))
    assert one.outcome.lower == pytest.approx(1) and one.values().count() == 1


def test_smooth_extrema_do_not_overflow(spark):
    from poslp.functions import smooth

    df = spark.createDataFrame([(float(x),) for x in (1.0, 2.0, 50.0)], "v double")
    assert smooth.smax(df, "v", 200.0) == pytest.approx(50.0) and smooth.smin(df, "v", 200.0) == pytest.approx(1.0)
    assert smooth.grad_smax(df, "v", 0.5).agg({"weight": "sum"}).first()[0] == pytest.approx(1.0)
    assert smooth.log_sum_exp(df.limit(0), df["v"], 1.0) == -math.inf


def test_layouts_give_the_same_product(spark, data):
    from pyspark.sql import functions as F

    from poslp.operators.layout import choose, grid2d, product_by_block, row1d
    from poslp.sources.graphs import part_supplier, with_eid

    edges = with_eid(part_supplier(spark, data))
    vector = edges.select(F.explode(F.array("u", "v")).alias("row")).distinct().withColumn("x", F.col("row") % 97 / F.lit(97.0))
    sums = [sorted((r["row"], round(r["x"], 9)) for r in product_by_block(place(edges, 4), vector, "x").collect()) for place in (grid2d, row1d)]
    assert sums[0] == sums[1] and choose(edges, 4).kind == "broadcast"


def test_generators(spark):
    assert synth.complete(spark, 6).count() == 15 and synth.star(spark, 5).count() == 5 and synth.complete_bipartite(spark, 3, 4).count() == 12
    assert synth.grid(spark, 4, 5, 0.0).count() == 4 * 4 + 3 * 5 and synth.path(spark, 3).count() == 3
    assert synth.rgg(spark, 7).count() > 100 and synth.kron(spark, 5, 4).count() > 20


def test_component_and_table_function_solves(spark):
    from poslp.functions.udfs import register, solve_components

    edges = spark.createDataFrame([(g, g * 10 + i, g * 10 + (i + 1) % 5) for g in (1, 2) for i in range(5)], "graph_id long, u long, v long")
    rows = solve_components(edges.withColumnRenamed("graph_id", "component"), "matching").collect()
    assert len(rows) == 2 and all(r["lower"] <= 2.5 * (1 + 1e-9) and r["upper"] >= 2.5 * (1 - 1e-9) for r in rows)
    register(spark)
    edges.createOrReplaceTempView("parts")
    assert spark.sql("SELECT * FROM solve_graph(TABLE(parts) PARTITION BY (graph_id), 'matching', 0.1D)").count() == 2
    assert spark.sql("SELECT max_violation(1.2D, 0.9D)").first()[0] == pytest.approx(0.2)


def test_stream_equals_batch(spark, data, tmp_path):
    from pyspark.sql import functions as F

    from poslp.streaming.windows import read_events, session_edges, window_edges

    src = str(tmp_path / "in")
    events = spark.read.parquet(f"{data}/events.parquet").orderBy("ts").coalesce(1)
    events.write.parquet(src)
    # a row far ahead closes every window
    late = events.limit(1).withColumn("ts", F.lit("2030-01-01").cast("timestamp_ntz"))
    late.write.mode("append").parquet(src)
    for make, name in ((window_edges, "w1"), (lambda s: session_edges(s, "6 hours"), "w2")):
        q = make(read_events(spark, src, 10)).writeStream.outputMode("append").format("memory").queryName(name).option("checkpointLocation", str(tmp_path / name)).start()
        q.processAllAvailable()
        q.processAllAvailable()
        q.stop()
        got = spark.table(name)
        batch = make(events.withColumn("ts", F.col("ts").cast("timestamp")))
        assert got.count() == batch.count() and got.exceptAll(batch).count() == 0


def test_coo_rows_can_be_empty():
    op = Coo([0], [0], [1.0], (2, 1))
    assert op.apply(np.array([2.0])).tolist() == [2.0, 0.0]
