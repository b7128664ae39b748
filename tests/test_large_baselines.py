"""Baselines on graphs of many edges: what they hold, and what they give."""

import tracemalloc

import numpy as np
import pytest

from poslp.baselines.matching import double_cover_value, hopcroft_karp
from poslp.baselines.peel import peel_sequential
from poslp.config import SolveConfig
from poslp.plans.problems import solve_local
from poslp.workloads import local_graph


def dense(n: int, share: float) -> tuple[np.ndarray, np.ndarray]:
    """A random graph with vertices of high number, which lists of numbers hold one by one."""
    keep = np.triu(np.random.default_rng(3).random((n, n)) < share, 1)
    return np.nonzero(keep)


@pytest.mark.parametrize("run", [peel_sequential, double_cover_value], ids=lambda f: f.__name__)
def test_baselines_hold_no_lists_of_edges(run):
    n = 900
    u, v = dense(n, 0.7)
    tracemalloc.start()
    run(u, v, n)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 100 * len(u)


def test_neighbours_repeat_and_missing_ends():
    """Repeated edges count twice; vertices without edges, and no edges at all, are no failure."""
    u, v = np.array([0, 0, 2]), np.array([1, 1, 3])
    assert peel_sequential(u, v, 6) == (1.0, 2)
    assert double_cover_value(u, v, 6) == 2.0
    assert hopcroft_karp(u, v, 6, np.arange(6) % 2 == 0) == 2
    none = np.empty(0, dtype=np.int64)
    assert peel_sequential(none, none, 3) == (0.0, 3) and double_cover_value(none, none, 3) == 0.0


def test_local_density_by_degrees_alone():
    """Where the split by degrees closes the bracket no step is taken, as on Spark's engine; its loads are a bound."""
    u, v = dense(300, 0.7)
    o = solve_local("densest", u, v, 300, SolveConfig(eps=0.1, step="newton"))
    assert o.iters == 0 and o.lower <= o.upper <= 1.1 * o.lower
    x = np.asarray(o.x) * o.scale
    assert np.allclose(x[0::2] + x[1::2], 1) and (x >= 0).all()
    load = np.bincount(np.r_[u, v], weights=np.r_[x[0::2], x[1::2]])
    assert load.max() == pytest.approx(o.upper) and len(u) / 300 <= o.upper
    assert solve_local("densest", u, v, 300, SolveConfig(eps=0.1, step="newton", early_certificate=False)).iters > 0


def test_local_graph_order_and_numbers(spark):
    edges = spark.createDataFrame([(7, 1 << 40), (3, 7), (3, 5)], "u long, v long")
    u, v, ids = local_graph(edges)
    assert list(zip(ids[u].tolist(), ids[v].tolist())) == [(3, 5), (3, 7), (7, 1 << 40)]
    assert [len(a) for a in local_graph(edges.limit(0))] == [0, 0, 0]
