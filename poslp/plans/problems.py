"""Graph problems as positive linear programs, solved on either engine. Solutions are fractional.

``engine="spark"`` keeps edges in Spark: in blocks with vertex vectors broadcast where those are of a checked size
(``blocks``), else with every vector in DataFrames (``distributed``). ``engine="local"`` runs numpy in one process, for
comparison. Variables have the same numbers everywhere: an edge's is its rank by (u, v), a vertex's its id, and an edge end's
is twice the edge's, one more for v.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from poslp.config import SolveConfig, Status, eta
from poslp.operators import frames as ops
from poslp.operators.matrices import ClosedNeighbourhood, Coo, Incidence, ObjectiveRow, PairSum, PairToVertex, RowScaled, Stack, Transposed
from poslp.plans.blocks import CoverBackend, EdgeBlocks, EdgeVariables, NeighbourBackend, SplitBackend
from poslp.plans.distributed import Side, SparkBackend
from poslp.plans.shared import discard, materialise
from poslp.plans.solver import LocalBackend, Outcome, release, search_target, solve_feasibility
from poslp.sources.graphs import vertices, with_eid

REPORT = "problem string, graph string, eps double, status string, objective double, lower double, upper double, max_violation double, iters bigint"
TRACE = "target double, iter bigint, alpha double, step_iters bigint, passes bigint, max_px double, min_cx double, potential double, max_violation double, objective double, lower double, upper double, t_matvec double, t_vec double, t_search double"


@dataclass
class Solution:
    """outcome: the driver's scalars and the point; ids: what the places of a local point stand for."""

    problem: str
    graph: str
    cfg: SolveConfig
    outcome: Outcome
    spark: SparkSession | None = None
    ids: np.ndarray | None = None

    def report(self) -> DataFrame:
        o = self.outcome
        row = (self.problem, self.graph, self.cfg.eps, str(o.status), float(o.best), float(o.lower), float(o.upper), float(o.max_violation), o.iters)
        return self.spark.createDataFrame([row], REPORT)

    def trace(self) -> DataFrame:
        names = [c.split()[0] for c in TRACE.split(", ")]
        rows = [tuple(t.get(n, 0.0) if n == "target" else t[n] for n in names) for t in self.outcome.trace]
        return self.spark.createDataFrame(rows, TRACE)

    def values(self) -> DataFrame:
        """(var, x), scaled to be feasible for packing and covering up to max_violation."""
        x = self.outcome.x
        if hasattr(x, "frame"):
            x = x.frame()
        if isinstance(x, DataFrame):
            return x.select("var", (F.col("x") * F.lit(float(self.outcome.scale))).alias("x"))
        scaled = np.asarray(x) * self.outcome.scale
        names = self.ids if self.ids is not None else np.arange(len(scaled))
        return self.spark.createDataFrame([(int(i), float(t)) for i, t in zip(names, scaled)], "var long, x double")

    def snapped(self) -> int | None:
        """The optimum of an integral problem, where the certified bracket holds one integer only."""
        lo, hi = math.ceil(self.outcome.lower - 1e-9), math.floor(self.outcome.upper + 1e-9)
        return lo if lo == hi else None


def support(values: DataFrame, least: float = 1e-6) -> DataFrame:
    return values.where(F.col("x") > least)


# ---- brackets ---------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Bracket:
    """What degrees alone prove of the optimum."""

    m: int
    n: int
    top: int
    fair: float  # the sum over edges of 1 / (the greater degree of its ends): a fractional matching
    side: float = math.inf  # vertices of the smaller side, where edges join even and odd numbers

    def of(self, problem: str, bound: str) -> tuple[float, float]:
        if problem in ("matching", "bimatching"):
            return self.fair, float(self.m) if bound == "paper" else min(float(self.m), self.n / 2, self.side)
        if problem == "vcover":
            return self.fair, min(self.n / 2, self.side)
        if problem == "domset":
            return self.n / (self.top + 1), float(self.n)
        raise ValueError(problem)


def solve_pure(problem: str, make, bracket: Bracket, cfg: SolveConfig) -> Outcome:
    """make(target) gives the backend of one feasibility problem."""
    kind = "packing" if problem in ("matching", "bimatching") else "covering"
    best: dict = {}

    def run(target: float, enough, eps: float) -> Outcome:
        x0 = best["x"] / 2 if cfg.warm_targets and "x" in best else None
        o = solve_feasibility(make(target), replace(cfg, eps=eps), kind, enough if cfg.early_certificate else None, x0)
        if cfg.warm_targets and isinstance(o.x, np.ndarray):
            best["x"] = o.x * o.scale
        return o

    return search_target(run, *bracket.of(problem, cfg.bound), cfg.eps, kind, lanes=cfg.target_lanes)


def search_density(make, lower: float, upper: float, cfg: SolveConfig, most: int = 40) -> Outcome:
    """Bisection over the density: edge splits bound the optimum from above; vertex weights and their level sets from
    below. make(density) gives a backend with lower(eta, stats)."""
    iters, trace, targets, x, scale, inner, evaluations, viol = 0, [], [], None, 1.0, cfg.eps, 0, 0.0
    for _ in range(most):
        if x is not None and upper <= (1 + cfg.eps) * lower:
            break
        density = math.sqrt(lower * upper)
        b = make(density)
        o = solve_feasibility(b, replace(cfg, eps=inner), "mixed")
        was, s = (lower, upper), o.last
        # at the smoothing of the run, and at a milder one
        lower = max([lower, *(b.lower(rate, replace(s, lse_y=s.max_y)) for rate in (eta(b.rows, inner), 10.0))])
        hi = density * s.max_y / s.min_z if s.min_z > 0 else math.inf
        better = hi <= upper or x is None and hi < math.inf
        release(x if better else o.x)
        if better:
            x, scale, viol, upper = o.x, o.scale, o.max_violation, min(upper, hi)
        iters += o.iters
        evaluations += o.evaluations
        trace += [t | {"target": density} for t in o.trace]
        targets.append((density, str(o.status), o.iters))
        if o.status == Status.ITER_LIMIT:
            break
        if math.isclose(lower / upper, was[0] / was[1], rel_tol=1e-3):
            inner /= 2
    closed = x is not None and upper <= (1 + cfg.eps) * lower * (1 + 1e-12)
    return Outcome(Status.FEASIBLE if closed else Status.ITER_LIMIT, iters, trace, lower, upper, upper, x, scale, viol, evaluations, len(targets), targets)


# ---- local engine ----------------------------------------------------------------------------------------------


def index_edges(pairs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(u, v, ids): ends as numbers from 0 and what they stand for."""
    ids, flat = np.unique(pairs, return_inverse=True)
    flat = flat.reshape(pairs.shape)
    return flat[:, 0], flat[:, 1], ids


class DensityBackend(LocalBackend):
    """Feasibility of a density: adds the bounds that any vertex weights and any edge split give."""

    def __init__(self, u, v, n: int, density: float):
        super().__init__(PairToVertex(u, v, n, density), PairSum(len(u)))
        self.u, self.v, self.density = u, v, density

    def lower(self, eta_: float, s) -> float:
        w = np.exp(np.maximum(eta_ * (self.y - s.lse_y), -500.0))
        w /= w.sum()
        return max(float(np.minimum(w[self.u], w[self.v]).sum()), level_density(self.u, self.v, self.p.shape[0], self.y))


def local_bracket(u: np.ndarray, v: np.ndarray, n: int) -> Bracket:
    deg = np.bincount(u, minlength=n) + np.bincount(v, minlength=n)
    return Bracket(len(u), n, int(deg.max()), float((1 / np.maximum(deg[u], deg[v])).sum()))


def local_split(u: np.ndarray, v: np.ndarray, n: int) -> tuple[np.ndarray, float]:
    """(share of each edge end, greatest load), as in degree_split."""
    deg = (np.bincount(u, minlength=n) + np.bincount(v, minlength=n)).astype(float)
    split = np.empty(2 * len(u))
    split[0::2] = deg[v] / (deg[u] + deg[v])
    split[1::2] = 1 - split[0::2]
    return split, float((np.bincount(u, weights=split[0::2], minlength=n) + np.bincount(v, weights=split[1::2], minlength=n)).max())


def solve_local(problem: str, u: np.ndarray, v: np.ndarray, n: int, cfg: SolveConfig, explicit: bool = False, tiled: int = 0) -> Outcome:
    from poslp.baselines.peel import peel_sequential
    from poslp.operators.matrices import Tiled

    form = (lambda op: Tiled(op.to_coo(), tiled)) if tiled else (lambda op: op.to_coo()) if explicit else (lambda op: op)
    m, bracket = len(u), local_bracket(u, v, n)
    if problem == "densest":
        peeled = peel_sequential(u, v, n)[0]
        if cfg.early_certificate:
            split, load = local_split(u, v, n)
            least = max(m / n, peeled, bracket.top / (bracket.top + 1))
            if load <= (1 + cfg.eps) * least:
                return Outcome(Status.FEASIBLE, 0, [], least, load, load, split, 1.0, 0.0, 0, 0, [])
        return search_density(lambda t: DensityBackend(u, v, n, t), max(m / n, peeled), min(2 * peeled, float(bracket.top)), cfg)
    if problem in ("matching", "bimatching"):
        op = form(Incidence(u, v, n))
        return solve_pure(problem, lambda t: LocalBackend(op, ObjectiveRow(m, t)), bracket, cfg)
    op = form(Transposed(Incidence(u, v, n)) if problem == "vcover" else ClosedNeighbourhood(u, v, n))
    return solve_pure(problem, lambda t: LocalBackend(ObjectiveRow(n, t), op, unit=True), bracket, cfg)


def level_density(u: np.ndarray, v: np.ndarray, n: int, load: np.ndarray) -> float:
    """The best density among the sets of most loaded vertices."""
    rank = np.empty(n, dtype=np.int64)
    rank[np.argsort(-load, kind="stable")] = np.arange(n)
    inside = np.cumsum(np.bincount(np.maximum(rank[u], rank[v]), minlength=n))
    return float((inside / np.arange(1, n + 1)).max())


def generalized_matching_lp(u, v, n: int, lo: np.ndarray, hi: np.ndarray, cap: float | None = None):
    """(packing, covering) of: at each vertex lo <= sum of its edges <= hi; optionally x <= cap on each edge."""
    op = Incidence(u, v, n)
    rows = np.flatnonzero(lo > 0)
    packing = RowScaled(op, hi)
    if cap is not None:
        m = len(u)
        packing = Stack(packing, Coo(np.arange(m), np.arange(m), np.full(m, 1 / cap), (m, m)))
    return packing, RowScaled(op, lo[rows], rows)


def solve_generalized(u, v, n: int, lo, hi, cfg: SolveConfig, cap: float | None = None) -> Outcome:
    return solve_feasibility(LocalBackend(*generalized_matching_lp(u, v, n, lo, hi, cap)), cfg, "mixed")


# ---- Spark engine ----------------------------------------------------------------------------------------------


def fits(n: int, cfg: SolveConfig) -> bool:
    """Whether vertex vectors are small enough for the driver to hold and broadcast."""
    return cfg.layout == "blocks" or cfg.layout == "auto" and 8 * n <= cfg.vertex_bytes


def graph_bracket(edges: DataFrame, verts: DataFrame) -> Bracket:
    """From the written tables of edges and vertices with degrees."""
    odd = F.col("vid") % 2 != 0
    n, top, right = verts.agg(F.count(F.lit(1)), F.max("degree"), F.count_if(odd)).first()
    at = lambda c: verts.select(F.col("vid").alias(c), F.col("degree").alias(f"_{c}"))
    sums = F.count(F.lit(1)), F.sum(1 / F.greatest("_u", "_v")), F.count_if((F.col("u") + F.col("v")) % 2 == 0)
    m, fair, same = edges.join(at("u"), "u").join(at("v"), "v").agg(*sums).first()
    return Bracket(m, n, top, fair, math.inf if same else float(min(right, n - right)))


def degree_split(edges: DataFrame, verts: DataFrame) -> tuple[DataFrame, float]:
    """((var, at, x), greatest load): each edge split between its ends in inverse proportion to their degrees. No density
    exceeds the greatest load of any split; on stars and complete graphs this one attains the optimum."""
    at = lambda c: verts.select(F.col("vid").alias(c), F.col("degree").alias(f"_{c}"))
    share = lambda k, c, other: F.struct((2 * F.col("eid") + k).alias("var"), F.col(c).alias("at"), (F.col(other) / (F.col("_u") + F.col("_v"))).alias("x"))
    both = edges.join(at("u"), "u").join(at("v"), "v").select(F.explode(F.array(share(0, "u", "_v"), share(1, "v", "_u"))).alias("e"))
    split = materialise(both.select("e.*"), "split")
    return split, split.groupBy("at").agg(F.sum("x").alias("load")).agg(F.max("load")).first()[0]


def plain_cover(verts: DataFrame, bracket: Bracket) -> DataFrame:
    """(var, x): one on the smaller side of a two-sided graph, or a half everywhere, whichever is less."""
    right = verts.agg(F.count_if(F.col("vid") % 2 != 0)).first()[0]
    smaller = (F.col("vid") % 2 != 0) if right == bracket.side else (F.col("vid") % 2 == 0)
    x = F.when(smaller, 1.0).otherwise(0.0) if bracket.side <= bracket.n / 2 else F.lit(0.5)
    return verts.select(F.col("vid").alias("var"), x.alias("x"))


def edge_blocks(edges: DataFrame, verts: DataFrame) -> EdgeBlocks:
    """edges: (eid, u, v); verts: (vid, ...), of a checked size."""
    return EdgeBlocks(edges, verts.select("vid").orderBy("vid").toArrow().column("vid").to_numpy())


def solve_spark(problem: str, edges: DataFrame, cfg: SolveConfig) -> Outcome:
    """edges: (u, v) in normal form."""
    from poslp.baselines.peel import peel_batched

    edges = materialise(with_eid(edges.select("u", "v")), "edges")
    verts = materialise(vertices(edges), "vertices")
    bracket = graph_bracket(edges, verts)
    n, every = bracket.n, cfg.checkpoint_every
    as_vars, as_rows = edges.select(F.col("eid").alias("var"), "u", "v"), verts.select(F.col("vid").alias("row"))
    blocks = edge_blocks(edges, verts) if fits(n, cfg) else None
    if problem == "densest":
        split, load = degree_split(edges, verts)
        star = bracket.top / (bracket.top + 1)  # a vertex with its neighbours
        if load <= (1 + cfg.eps) * max(bracket.m / n, star):
            return Outcome(Status.FEASIBLE, 0, [], max(bracket.m / n, star), load, load, split, 1.0, 0.0, 0, 0, [])
        discard(split)
        peeled = peel_batched(edges, 0.1)[0]
        lower, upper = max(bracket.m / n, peeled, star), min(2.2 * peeled, float(bracket.top))
        ends = F.explode(F.array(F.struct((2 * F.col("eid")).alias("var"), F.col("u").alias("at")), F.struct((2 * F.col("eid") + 1).alias("var"), F.col("v").alias("at"))))
        pairs = edges.select(F.col("eid").alias("edge"), ends.alias("e")).select("e.var", "edge", "e.at")
        rows = edges.select(F.col("eid").alias("row"))
        frames = lambda t: SplitFrames(pairs, Side(ops.PairToVertexFrames(t), as_rows), Side(ops.PairSumFrames(), rows), 1.0 / t, every, edges)
        return search_density((lambda t: SplitBackend(blocks, t)) if blocks else frames, lower, upper, cfg)
    if problem in ("matching", "bimatching"):
        hi = np.ones(n) if blocks else None
        make = (lambda t: EdgeVariables(blocks, hi, t)) if blocks else lambda t: SparkBackend(as_vars, Side(ops.IncidenceFrames(), as_rows), Side(target=t), 1.0, every)
    elif problem == "vcover":
        value = min(n / 2, bracket.side)
        if value <= (1 + cfg.eps) * bracket.fair:
            return Outcome(Status.FEASIBLE, 0, [], bracket.fair, value, value, plain_cover(verts, bracket), 1.0, 0.0, 0, 0, [])
        rows = edges.select(F.col("eid").alias("row"), "u", "v")
        make = (lambda t: CoverBackend(blocks, t)) if blocks else lambda t: SparkBackend(verts.select(F.col("vid").alias("var")), Side(target=t), Side(ops.CoverFrames(), rows), 1.0 / t, every)
    elif problem == "domset":
        op = ops.NeighbourhoodFrames(edges)
        make = (lambda t: NeighbourBackend(blocks, ObjectiveRow(n, t))) if blocks else lambda t: SparkBackend(verts.select(F.col("vid").alias("var")), Side(target=t), Side(op, as_rows), 1.0 / t, every)
    else:
        raise ValueError(problem)
    return solve_pure(problem, make, bracket, cfg)


class SplitFrames(SparkBackend):
    """Densest subgraph on frames; lower() as on the other engines, by vertex weights alone."""

    def __init__(self, variables, packing, covering, column_max, every, edges: DataFrame):
        super().__init__(variables, packing, covering, column_max, every)
        self.edges = edges

    def lower(self, eta_: float, s) -> float:
        w = self.frames[0].select("row", F.exp(F.greatest(F.lit(eta_) * (F.col("val") - F.lit(s.lse_y)), F.lit(-500.0))).alias("w"))
        at = lambda c: w.select(F.col("row").alias(c), F.col("w").alias(f"_{c}"))
        least = self.edges.join(at("u"), "u").join(at("v"), "v").agg(F.sum(F.least("_u", "_v"))).first()[0]
        return least / w.agg(F.sum("w")).first()[0]


def generalized_matching_spark(edges: DataFrame, bounds: DataFrame, cfg: SolveConfig) -> Outcome:
    """edges (u, v); bounds (vid, lo, hi): lo <= sum of the edges at vid <= hi, hi positive."""
    edges = materialise(with_eid(edges.select("u", "v")), "edges")
    bounds = materialise(bounds.select("vid", F.col("lo").cast("double").alias("lo"), F.col("hi").cast("double").alias("hi")), "bounds")
    if fits(bounds.count(), cfg):
        held = bounds.orderBy("vid").toArrow()
        lo, hi = (held.column(c).to_numpy() for c in ("lo", "hi"))
        return solve_feasibility(EdgeVariables(EdgeBlocks(edges, held.column("vid").to_numpy()), hi, lo=lo), cfg, "mixed")
    variables = edges.select(F.col("eid").alias("var"), "u", "v")
    packing = bounds.select(F.col("vid").alias("row"), F.col("hi").alias("bound"))
    covering = bounds.where(F.col("lo") > 0).select(F.col("vid").alias("row"), F.col("lo").alias("bound"))
    # vertices without a lower bound have no covering row: their edges get nothing from that end
    op = ops.ScaledRowsFrames(ops.IncidenceFrames(partial=True))
    at_u, at_v = (packing.select(F.col("row").alias(c), (1 / F.col("bound")).alias(f"_{c}")) for c in "uv")
    top = variables.join(at_u, "u").join(at_v, "v").select("var", "u", "v", F.greatest("_u", "_v").alias("top"))
    return solve_feasibility(SparkBackend(top, Side(ops.ScaledRowsFrames(ops.IncidenceFrames()), packing), Side(op, covering), "top", cfg.checkpoint_every), cfg, "mixed")


def solve(problem: str, edges: DataFrame, cfg: SolveConfig | None = None, graph: str = "") -> Solution:
    """problem: matching, bimatching, vcover, domset or densest; edges: (u, v) in normal form."""
    cfg = cfg or SolveConfig()
    spark = edges.sparkSession
    if problem == "bimatching" and not two_colourable(edges):
        raise ValueError("the graph has an odd cycle")
    edges = materialise(edges.select("u", "v"), "graph")
    m = edges.count()
    if m == 0:
        return Solution(problem, graph, cfg, Outcome(Status.FEASIBLE, 0, [], 0.0, 0.0, 0.0, np.empty(0)), spark)
    if cfg.engine == "local":
        if m > cfg.local_edges:
            raise ValueError(f"{m} edges are too many for one process")
        pairs = edges.orderBy("u", "v").toArrow()  # at most local_edges rows
        u, v, ids = index_edges(np.stack([pairs.column(c).to_numpy() for c in "uv"], axis=1))
        return Solution(problem, graph, cfg, solve_local(problem, u, v, len(ids), cfg), spark, ids if problem in ("vcover", "domset") else None)
    return Solution(problem, graph, cfg, solve_spark(problem, edges, cfg), spark)


def two_colourable(edges: DataFrame) -> bool:
    """Even left and odd right numbers are a colouring; any other graph is two-coloured if no vertex is in one
    component with itself at the other parity, in the graph of (vertex, parity)."""
    if not edges.where((F.col("u") + F.col("v")) % 2 == 0).limit(1).count():
        return True
    doubled = edges.select(F.explode(F.array(*[F.struct((2 * F.col("u") + p).alias("a"), (2 * F.col("v") + 1 - p).alias("b")) for p in (0, 1)])).alias("e")).select("e.*")
    label = materialise(components(doubled), "labels")
    vid, parity = F.floor(F.col("node") / 2), F.col("node") % 2
    both = label.groupBy(vid.alias("vid")).agg(F.min(F.when(parity == 0, F.col("component"))).alias("p"), F.min(F.when(parity == 1, F.col("component"))).alias("q"))
    return not both.where(F.col("p") == F.col("q")).limit(1).count()


def components(edges: DataFrame) -> DataFrame:
    """(node, component) of edges (a, b), component the least node, by alternating stars: rounds grow with the logarithm of
    the longest path, not with its length, and go on until nothing changes."""
    now, old, state = edges.select("a", "b").where(F.col("a") != F.col("b")), None, None
    while True:
        ways = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()
        ways = materialise(ways, "ways")
        least = ways.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
        large = ways.join(least, "a").where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = materialise(large.where(F.col("a") != F.col("b")).distinct(), "large-star")
        small = large.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        least = small.groupBy("a").agg(F.min("b").alias("m"))
        joined = small.join(least, "a")
        small = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
        now = materialise(small.where(F.col("a") != F.col("b")).distinct(), "small-star")
        discard(ways, large, old)
        old, was = now, state
        state = tuple(now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
        if state == was:
            return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
