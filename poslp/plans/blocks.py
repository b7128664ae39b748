"""The solver's backends over edge blocks: edges stay in Spark, vertex vectors travel.

Edges are written once, in blocks of a square grid over their ends, and never rewritten. An iteration is one job over
them (and one more for a step search over edge rows): vertex vectors go out as a broadcast, each task adds up its
block's contributions by vertex, and the sums of all tasks come back. An edge variable is a product of factors that
depend on its ends' weights alone, so it is replayed from the weights of the iterations since the last written state;
states are written every ``REPLAY`` iterations, and earlier ones deleted but for the best.

This layout needs vertex vectors of a checked size (``SolveConfig.vertex_bytes``); larger graphs go to the frames of
``distributed``, which keep every vector in DataFrames.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poslp.operators.layout import grid2d
from poslp.plans.shared import discard, materialise
from poslp.plans.solver import Direction, LocalBackend, Stats, _exp
from poslp.plans.steps import Trial

#: Edges to a block, about.
BLOCK_EDGES = 1 << 17
#: Partial sums of all blocks up to which they are added on the driver, without a shuffle.
FEW_SUMS = 1 << 20
#: Iterations replayed at most, and the bytes of their weights.
REPLAY = 32
REPLAY_BYTES = 256 << 20
SUMS = "i long, s double, top double, low double, most double"
LANE = "lane int, least double, low double, s double, t double"


class _Sums:
    """Sums by vertex over the batches of a task, and four scalars: a sum, a maximum, a minimum, another maximum."""

    def __init__(self, shared: dict):
        self.shared, self.out = shared, np.zeros(shared["n"])
        self.sum, self.top, self.low, self.most = 0.0, -math.inf, math.inf, -math.inf

    def spread(self, u, v, at_u, at_v) -> None:
        n = len(self.out)
        self.out += np.bincount(u, weights=at_u, minlength=n)
        self.out += np.bincount(v, weights=at_v, minlength=n)

    def end(self) -> Iterator[pa.RecordBatch]:
        i = np.flatnonzero(self.out)
        none = np.full(len(i), np.nan)
        rows = [np.r_[i, -1], np.r_[self.out[i], self.sum], np.r_[none, self.top], np.r_[none, self.low], np.r_[none, self.most]]
        blank = np.r_[np.ones(len(i), dtype=bool), False]
        yield pa.RecordBatch.from_arrays([pa.array(rows[0]), pa.array(rows[1]), *(pa.array(r, mask=blank) for r in rows[2:])], names=["i", "s", "top", "low", "most"])


class NeighbourSums(_Sums):
    def add(self, _, u, v, *state) -> None:
        x = self.shared["x"]
        self.spread(u, v, x[v], x[u])


class CoverWeights(_Sums):
    """Sums of the edge rows' weights, z = x_u + x_v."""

    def add(self, _, u, v, *state) -> None:
        s = self.shared
        z = s["x"][u] + s["x"][v]
        w = np.where(s["dropping"] & (z >= 1), 0.0, _exp(-s["eta"] * (z - s["lse"])))
        self.spread(u, v, w, w)


class CoverBounds(_Sums):
    """How many edges have their last end at each rank, and the sum of the lesser weight of each edge's ends."""

    def add(self, _, u, v, *state) -> None:
        rank, w = self.shared["rank"], self.shared["w"]
        self.out += np.bincount(np.maximum(rank[u], rank[v]), minlength=len(self.out))
        self.sum += float(np.minimum(w[u], w[v]).sum())


def edge_factor(u, v, g: np.ndarray, h) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(growth, price, gain) of edges: g, h by vertex, or h for all."""
    price = g[u] + g[v]
    gain = h[u] + h[v] if isinstance(h, np.ndarray) else np.full(len(u), h)
    return np.where(gain > 0, np.maximum(0.0, 1 - price / np.where(gain > 0, gain, 1)), 0.0), price, gain


def replayed(shared: dict, u, v, state) -> np.ndarray:
    """Edge variables now."""
    x = state[0] if state else shared["x0"] / np.maximum(shared["top"][u], shared["top"][v])
    for c, g, h in shared["past"]:
        x = x * (1 + c * edge_factor(u, v, g, h)[0])
    return x


class EdgeDirection(_Sums):
    def add(self, _, u, v, *state) -> None:
        s = self.shared
        f, price, gain = edge_factor(u, v, s["g"], s["h"])
        d = replayed(s, u, v, state) * f * s["c"]
        self.spread(u, v, d, d)
        self.sum += float(d.sum())
        self.top, self.low, self.most = max(self.top, float(d.max(initial=-math.inf))), min(self.low, float(price.min(initial=math.inf))), max(self.most, float(gain.max(initial=-math.inf)))


def replayed_pair(shared: dict, u, v, state) -> tuple[np.ndarray, np.ndarray]:
    """Both variables of each edge now."""
    a, b = state if state else (np.full(len(u), shared["x0"]), np.full(len(u), shared["x0"]))
    for c, g, eta, lse, dropping in shared["past"]:
        fa, fb, _ = pair_factor(u, v, a + b, g, eta, lse, dropping)
        a, b = a * (1 + c * fa), b * (1 + c * fb)
    return a, b


def pair_factor(u, v, z, g, eta, lse, dropping):
    h = np.where(dropping & (z >= 1), 0.0, _exp(-eta * (z - lse)))
    safe = np.where(h > 0, h, 1)
    grow = lambda at: np.where(h > 0, np.maximum(0.0, 1 - g[at] / safe), 0.0)
    return grow(u), grow(v), h


class PairDirection(_Sums):
    def add(self, _, u, v, *state) -> None:
        s = self.shared
        a, b = replayed_pair(s, u, v, state)
        fa, fb, h = pair_factor(u, v, a + b, s["g"], s["eta"], s["lse"], s["dropping"])
        da, db = a * fa * s["c"], b * fb * s["c"]
        self.spread(u, v, da, db)
        self.sum += float(da.sum() + db.sum())
        self.top = max(self.top, float(da.max(initial=-math.inf)), float(db.max(initial=-math.inf)))
        self.most = max(self.most, float(h.max(initial=-math.inf)))


class PairStart(_Sums):
    def add(self, _, u, v, *state) -> None:
        a, b = replayed_pair(self.shared, u, v, state)
        self.spread(u, v, a, b)
        self.sum += float(a.sum() + b.sum())


class _Lanes:
    """For each step: the least covering row, the least active one, and the exponential sums of the active ones."""

    def __init__(self, shared: dict):
        self.shared, n = shared, len(shared["alphas"])
        self.least, self.low = np.full(n, math.inf), np.full(n, math.inf)
        self.s, self.t = np.zeros(n), np.zeros(n)

    def rows(self, u, v, state) -> tuple[np.ndarray, np.ndarray]:
        x, d = self.shared["x"], self.shared["d"]
        return x[u] + x[v], d[u] + d[v]

    def add(self, _, u, v, *state) -> None:
        z, dz = self.rows(u, v, state)
        eta = self.shared["eta"]
        active = z < 1 if self.shared["dropping"] else np.ones(len(z), dtype=bool)
        for k, a in enumerate(self.shared["alphas"]):
            zz = z + a * dz
            self.least[k] = min(self.least[k], zz.min(initial=math.inf))
            if not active.any():
                continue
            zz, dd = zz[active], dz[active]
            low = min(self.low[k], float(zz.min()))
            fade = math.exp(max(-700.0, -eta * (self.low[k] - low))) if self.low[k] < math.inf else 0.0
            e = _exp(-eta * (zz - low))
            self.s[k], self.t[k], self.low[k] = self.s[k] * fade + float(e.sum()), self.t[k] * fade + float(e @ dd), low

    def end(self) -> Iterator[pa.RecordBatch]:
        lane = np.arange(len(self.least), dtype=np.int32)
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (lane, self.least, self.low, self.s, self.t)], names=["lane", "least", "low", "s", "t"])


class PairLanes(_Lanes):
    def rows(self, u, v, state) -> tuple[np.ndarray, np.ndarray]:
        s = self.shared
        a, b = replayed_pair(s, u, v, state)
        if s["g"] is None:
            return a + b, np.zeros(len(u))
        fa, fb, _ = pair_factor(u, v, a + b, s["g"], s["at"], s["lse"], s["dropping"])
        return a + b, s["c"] * (a * fa + b * fb)


def _over(kernel, shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        k = kernel(shared.value)
        for b in batches:
            k.add(*(c.to_numpy(zero_copy_only=False) for c in b.columns))
        yield from k.end()

    return run


def _stated(pair: bool, shared):
    """The state now, as a table: (eid, u, v, x) or (eid, u, v, x, x2)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            eid, u, v, *state = (c.to_numpy(zero_copy_only=False) for c in b.columns)
            now = replayed_pair(shared.value, u, v, state) if pair else (replayed(shared.value, u, v, state),)
            yield pa.RecordBatch.from_arrays([*b.columns[:3], *(pa.array(x) for x in now)], names=["eid", "u", "v", "x", "x2"][: 3 + len(now)])

    return run


class EdgeBlocks:
    """edges: (eid, u, v); ids: the vertices in order, of a checked size. The table holds ends as places in ids."""

    def __init__(self, edges: DataFrame, ids: np.ndarray):
        self.spark, self.ids, self.n = edges.sparkSession, ids, len(ids)
        self.m = edges.count()
        self.side = side = max(1, math.isqrt(max(1, -(-self.m // BLOCK_EDGES))))
        placed = grid2d(edges.select("eid", "u", "v"), side * side) if side > 1 else edges.select("eid", "u", "v").coalesce(1)
        shared = self.share({"ids": ids})

        def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                ends = [np.searchsorted(shared.value["ids"], b.column(k).to_numpy()) for k in (1, 2)]
                yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(e) for e in ends)], names=["eid", "u", "v"])

        self.table = materialise(placed.select("eid", "u", "v").mapInArrow(index, "eid long, u long, v long"), "blocks")

    def share(self, values: dict):
        return self.spark.sparkContext.broadcast(values)

    def state(self, pair: bool, start: dict) -> EdgeState:
        return EdgeState(self, pair, start)

    def sums(self, kernel, table: DataFrame, **shared) -> tuple[np.ndarray, float, float, float, float]:
        """(by vertex, sum, top, low, most) of a kernel over the table: one job."""
        held = self.share(shared | {"n": self.n})
        try:
            parts = table.mapInArrow(_over(kernel, held), SUMS)
            if self.side > 1 and self.side**2 * self.n > FEW_SUMS:
                parts = parts.groupBy("i").agg(F.sum("s").alias("s"), F.max("top").alias("top"), F.min("low").alias("low"), F.max("most").alias("most"))
            got = parts.toArrow()  # a row a vertex, of a checked size; from each block while those are few
        finally:
            held.destroy()
        i, s = got.column("i").to_numpy(), got.column("s").to_numpy()
        rest = np.flatnonzero(i < 0)
        top, low, most = (got.column(c).to_numpy(zero_copy_only=False)[rest] if len(rest) else np.empty(0) for c in ("top", "low", "most"))
        sums = np.bincount(i[i >= 0], weights=s[i >= 0], minlength=self.n)
        return sums, float(s[rest].sum()), float(top.max(initial=-math.inf)), float(low.min(initial=math.inf)), float(most.max(initial=-math.inf))

    def lanes(self, kernel, table: DataFrame, **shared) -> list[tuple[float, float, float, float]]:
        """(least, log-sum-exp value, slope, least active) of each step: one job; tasks return a row a step."""
        held = self.share(shared)
        eta, n = shared["eta"], len(shared["alphas"])
        try:
            got = table.mapInArrow(_over(kernel, held), LANE).toArrow()
        finally:
            held.destroy()
        lane, least, low, s, t = (got.column(c).to_numpy() for c in ("lane", "least", "low", "s", "t"))
        out = []
        for k in range(n):
            mine = lane == k
            floor = low[mine].min(initial=math.inf)
            if floor == math.inf:
                out.append((float(least[mine].min(initial=math.inf)), math.inf, 0.0, math.inf))
                continue
            fade = _exp(-eta * (np.where(np.isfinite(low[mine]), low[mine], math.inf) - floor)) * np.isfinite(low[mine])
            total, slope = float((s[mine] * fade).sum()), float((t[mine] * fade).sum())
            out.append((float(least[mine].min()), floor - math.log(total) / eta, slope / total, float(floor)))
        return out


class NeighbourProduct:
    """Identity plus adjacency over edge blocks, with the interface of a local operator."""

    def __init__(self, blocks: EdgeBlocks):
        self.blocks, self.shape, self.nnz = blocks, (blocks.n, blocks.n), blocks.n + 2 * blocks.m

    def apply(self, x: np.ndarray) -> np.ndarray:
        return x + self.blocks.sums(NeighbourSums, self.blocks.table, x=x)[0]

    apply_t = apply

    def col_max(self) -> np.ndarray:
        return np.ones(self.blocks.n)


class RowSums(_Sums):
    def add(self, _, row, col, a) -> None:
        self.out += np.bincount(row, weights=a * self.shared["x"][col], minlength=len(self.out))


class ColumnSums(_Sums):
    def add(self, _, row, col, a) -> None:
        self.out += np.bincount(col, weights=a * self.shared["x"][row], minlength=len(self.out))


class EntryProduct(EdgeBlocks):
    """An explicit matrix of entries (row, var, val) as blocks, with the interface of a local operator; rows and columns:
    their keys in order, both of a checked size."""

    def __init__(self, entries: DataFrame, rows: np.ndarray, columns: np.ndarray):
        self.spark, self.m = entries.sparkSession, entries.count()
        self.shape, self.nnz = (len(rows), len(columns)), self.m
        self.side = max(1, math.isqrt(max(1, -(-self.m // BLOCK_EDGES))))
        shared = self.share({"rows": rows, "columns": columns})

        def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                at = [np.searchsorted(shared.value[k], b.column(i).to_numpy()) for i, k in enumerate(("rows", "columns"))]
                yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(x) for x in at), b.column(2)], names=["eid", "u", "v", "a"])

        placed = entries.select("row", "var", "val")
        placed = placed.coalesce(1) if self.side == 1 else grid2d(placed.withColumnsRenamed({"row": "u", "var": "v"}), self.side**2).select("u", "v", "val")
        self.table = materialise(placed.mapInArrow(index, "eid long, u long, v long, a double"), "entry-blocks")

    def apply(self, x: np.ndarray) -> np.ndarray:
        self.n = self.shape[0]
        return self.sums(RowSums, self.table, x=x)[0]

    def apply_t(self, w: np.ndarray) -> np.ndarray:
        self.n = self.shape[1]
        return self.sums(ColumnSums, self.table, x=w)[0]

    def col_max(self) -> np.ndarray:
        top = self.table.groupBy("v").agg(F.max("a").alias("a")).toArrow()  # one row a column
        out = np.zeros(self.shape[1])
        out[top.column("v").to_numpy()] = top.column("a").to_numpy()
        return out


class ColumnBackend(LocalBackend):
    """Row and column vectors on the driver, products by jobs; columns: the keys of the variables."""

    def __init__(self, packing, covering, columns: np.ndarray):
        super().__init__(packing, covering)
        self.columns = columns
        self.spark = next(o.spark for o in (packing, covering) if isinstance(o, EntryProduct))

    def keep(self, x: np.ndarray | None = None) -> KeyedValues:
        return KeyedValues(self.spark, self.columns, self.x.copy())


class KeyedValues:
    def __init__(self, spark, keys: np.ndarray, x: np.ndarray):
        self.spark, self.keys, self.x = spark, keys, x

    def frame(self) -> DataFrame:
        return self.spark.createDataFrame(pa.table({"var": pa.array(self.keys), "x": pa.array(self.x)}))


class VertexValues:
    """Vertex variables of an outcome, held as one array of a checked size."""

    def __init__(self, blocks: EdgeBlocks, x: np.ndarray):
        self.blocks, self.x = blocks, x

    def frame(self) -> DataFrame:
        return self.blocks.spark.createDataFrame(pa.table({"var": pa.array(self.blocks.ids), "x": pa.array(self.x)}))


class NeighbourBackend(LocalBackend):
    """Dominating set: all vectors are vertex vectors, products are jobs."""

    def __init__(self, blocks: EdgeBlocks, packing):
        super().__init__(packing, NeighbourProduct(blocks), unit=True)
        self.blocks = blocks

    def keep(self, x: np.ndarray | None = None) -> VertexValues:
        return VertexValues(self.blocks, self.x.copy() if x is None else x)


class EdgeState:
    """Edge variables as a written table (or the start) and the factors since."""

    def __init__(self, blocks: EdgeBlocks, pair: bool, start: dict):
        self.blocks, self.pair, self.start = blocks, pair, start
        self.table, self.past = blocks.table, []
        self.best: tuple | None = None

    def shared(self) -> dict:
        return self.start | {"past": self.past}

    def push(self, factor: tuple) -> None:
        self.past = [*self.past, factor]
        size = sum(x.nbytes for f in self.past for x in f if isinstance(x, np.ndarray))
        if len(self.past) >= REPLAY or size > REPLAY_BYTES:
            old, self.table, self.past = self.table, self._written(self.table, self.past), []
            if old is not self.blocks.table and not (self.best and self.best[0] is old):
                discard(old)

    def _written(self, table: DataFrame, past: list) -> DataFrame:
        held = self.blocks.share(self.start | {"past": past})
        out = materialise(table.mapInArrow(_stated(self.pair, held), "eid long, u long, v long, x double" + ", x2 double" * self.pair), "edge-state")
        held.destroy()
        return out

    def keep(self) -> EdgeValues:
        old, self.best = self.best, (self.table, self.past)
        if old and old[0] is not self.blocks.table and old[0] is not self.table:
            discard(old[0])
        return EdgeValues(self, *self.best)

    def close(self) -> None:
        if self.table is not self.blocks.table and not (self.best and self.best[0] is self.table):
            discard(self.table)


class EdgeValues:
    def __init__(self, state: EdgeState, table: DataFrame, past: list):
        self.state, self.table, self.past = state, table, past

    def frame(self) -> DataFrame:
        """(var, x): edge ids, or twice the edge id for the first end and one more for the second."""
        s = self.state
        held = s.blocks.share(s.start | {"past": self.past})
        rows = self.table.mapInArrow(_stated(s.pair, held), "eid long, u long, v long, x double" + ", x2 double" * s.pair)
        if not s.pair:
            return rows.select(F.col("eid").alias("var"), "x")
        ends = F.array(F.struct((2 * F.col("eid")).alias("var"), F.col("x")), F.struct((2 * F.col("eid") + 1).alias("var"), F.col("x2").alias("x")))
        return rows.select(F.explode(ends).alias("e")).select("e.*")

    def release(self) -> None:
        if self.table is not self.state.blocks.table:
            discard(self.table)


class EdgeVariables(LocalBackend):
    """Variables are edges, rows are vertices. hi: the packing bound of each vertex; the covering side is the objective
    row of a target, or the sums at vertices over lo (where lo is positive)."""

    def __init__(self, blocks: EdgeBlocks, hi: np.ndarray, target: float | None = None, lo: np.ndarray | None = None):
        self.blocks, self.hi, self.target, self.lo = blocks, hi, target, lo
        self.covered = np.flatnonzero(lo > 0) if lo is not None else np.zeros(1, dtype=int)
        self.rows = blocks.n + len(self.covered)
        self.one_row = target is not None
        self.nnz = 2 * blocks.m * (1 if self.one_row else 2)

    def start(self, eps: float) -> None:
        self.state = self.blocks.state(False, {"x0": eps / max(1, self.blocks.m), "top": 1 / self.hi})
        # growth one times the start is the start: its sums by vertex
        sums, total, *_ = self.blocks.sums(EdgeDirection, self.state.table, g=np.zeros(self.blocks.n), h=1.0, c=1.0, **self.state.shared())
        self.y, self.sum_x = sums / self.hi, total
        self.z = np.array([total / self.target]) if self.one_row else (sums / np.where(self.lo > 0, self.lo, 1))[self.covered]
        self.active = np.ones(len(self.z), dtype=bool)

    def stats(self, eta_: float) -> Stats:
        self.x = np.array([self.sum_x])  # only its sum is asked for
        return super().stats(eta_)

    def direction(self, eta_: float, s: Stats, scale: float) -> Direction:
        begun = time.perf_counter()
        self.wp = _exp(eta_ * (self.y - s.lse_y))
        g = self.wp / self.hi
        if self.one_row:
            h = 1 / self.target
        else:
            h = np.zeros(self.blocks.n)
            h[self.covered] = np.where(self.active, _exp(-eta_ * (self.z - s.lse_z)), 0.0) / self.lo[self.covered]
        self.now = scale / (2 * eta_), g, h
        sums, self.sum_d, top, low, most = self.blocks.sums(EdgeDirection, self.state.table, g=g, h=h, c=self.now[0], **self.state.shared())
        self.dy = sums / self.hi
        self.dz = np.array([self.sum_d / self.target]) if self.one_row else (sums / np.where(self.lo > 0, self.lo, 1))[self.covered]
        self.t_matvec, self.t_vec = time.perf_counter() - begun, 0.0
        return Direction(top, self.sum_d, low, most)

    def advance(self, alpha: float) -> None:
        c, g, h = self.now
        self.state.push((alpha * c, g, h))
        self.sum_x += alpha * self.sum_d
        self.y, self.z = self.y + alpha * self.dy, self.z + alpha * self.dz

    def keep(self) -> EdgeValues:
        return self.state.keep()

    def close(self) -> None:
        self.state.close()


class _EdgeRows(LocalBackend):
    """Covering rows are edges: their smoothed minimum comes from a job, and the one of an accepted step is kept."""

    dropping = False

    def _edge_lanes(self, eta_: float, alphas: list[float], still: bool) -> list[tuple[float, float, float, float]]:
        raise NotImplementedError

    def stats(self, eta_: float) -> Stats:
        my = float(self.y.max())
        ly = my + math.log(_exp(eta_ * (self.y - my)).sum()) / eta_
        if self.known is None:
            self.known = self._edge_lanes(eta_, [0.0], True)[0]
        least, lse, _, _ = self.known
        return Stats(my, ly, least, lse, self.sum_x)

    def lanes(self, eta_: float, s: Stats, alphas: list[float]) -> list[Trial]:
        out = []
        for a, (least, lse, slope, low) in zip(alphas, self._edge_lanes(eta_, alphas, False)):
            y = self.y + a * self.dy
            my = float(y.max())
            e = _exp(eta_ * (y - my))
            out.append(Trial(a, lse - s.lse_z, my + math.log(e.sum()) / eta_ - s.lse_y, slope, float(e @ self.dy / e.sum()), least))
            self.tried[a] = least, lse, slope, low
        return out

    def drop(self) -> int:
        """Rows at one or more count no longer; their least value is known only where one is left."""
        self.dropping, self.known = True, None
        return 1

    def _moved(self, alpha: float) -> None:
        self.known, self.tried = (None if self.dropping else self.tried.get(alpha)), {}
        self.sum_x += alpha * self.sum_d
        self.y = self.y + alpha * self.dy


class CoverBackend(_EdgeRows):
    """Vertex cover: variables are vertices."""

    unit = True

    def __init__(self, blocks: EdgeBlocks, target: float):
        self.blocks, self.target, self.one_row = blocks, target, True
        self.rows, self.nnz = blocks.m + 1, 2 * blocks.m

    def start(self, eps: float) -> None:
        self.x = np.full(self.blocks.n, eps * self.target / self.blocks.n)
        self.sum_x = float(self.x.sum())
        self.y = np.array([self.sum_x / self.target])
        self.d, self.known, self.tried = np.zeros(self.blocks.n), None, {}

    def _edge_lanes(self, eta_, alphas, still):
        return self.blocks.lanes(_Lanes, self.blocks.table, alphas=alphas, eta=eta_, x=self.x, d=self.d, dropping=self.dropping)

    def direction(self, eta_: float, s: Stats, scale: float) -> Direction:
        begun = time.perf_counter()
        h = self.blocks.sums(CoverWeights, self.blocks.table, x=self.x, eta=eta_, lse=s.lse_z, dropping=self.dropping)[0]
        g, self.h = 1 / self.target, h
        self.d = np.where(h > 0, np.maximum(0.0, 1 - g / np.where(h > 0, h, 1)), 0.0) * self.x * scale / (2 * eta_)
        self.sum_d = float(self.d.sum())
        self.dy = np.array([self.sum_d / self.target])
        self.t_matvec, self.t_vec = time.perf_counter() - begun, 0.0
        return Direction(float(self.d.max()), self.sum_d, g, float(h.max()))

    def advance(self, alpha: float) -> None:
        self._average(alpha * self.sum_d)
        self.x = self.x + alpha * self.d
        self._moved(alpha)

    def keep(self, x: np.ndarray | None = None) -> VertexValues:
        return VertexValues(self.blocks, self.x.copy() if x is None else x)


class SplitBackend(_EdgeRows):
    """Densest subgraph: each edge splits between its ends, vertices bear at most the density."""

    def __init__(self, blocks: EdgeBlocks, density: float):
        self.blocks, self.density, self.one_row = blocks, density, False
        self.rows, self.nnz = blocks.n + blocks.m, 4 * blocks.m

    def start(self, eps: float) -> None:
        self.state = self.blocks.state(True, {"x0": eps * self.density / (2 * max(1, self.blocks.m))})
        sums, self.sum_x, *_ = self.blocks.sums(PairStart, self.state.table, **self.state.shared())
        self.y = sums / self.density
        self.known, self.tried, self.now = None, {}, None

    def _edge_lanes(self, eta_, alphas, still):
        c, g, at, lse = (0.0, None, eta_, 0.0) if still else self.now
        return self.blocks.lanes(PairLanes, self.state.table, alphas=alphas, eta=eta_, at=at, g=g, c=c, lse=lse, dropping=self.dropping, **self.state.shared())

    def direction(self, eta_: float, s: Stats, scale: float) -> Direction:
        begun = time.perf_counter()
        self.wp = _exp(eta_ * (self.y - s.lse_y))
        g = self.wp / self.density
        self.now = scale / (2 * eta_), g, eta_, s.lse_z
        sums, self.sum_d, top, _, most = self.blocks.sums(PairDirection, self.state.table, g=g, eta=eta_, lse=s.lse_z, c=self.now[0], dropping=self.dropping, **self.state.shared())
        self.dy = sums / self.density
        self.t_matvec, self.t_vec = time.perf_counter() - begun, 0.0
        return Direction(top, self.sum_d, float(g.min()), most)

    def advance(self, alpha: float) -> None:
        c, g, eta_, lse = self.now
        self.state.push((alpha * c, g, eta_, lse, self.dropping))
        self._moved(alpha)

    def lower(self, eta_: float, s: Stats) -> float:
        """What any vertex weights prove of the density, and the best of the sets of most loaded vertices."""
        w = _exp(eta_ * (self.y - s.lse_y))
        rank = np.empty(self.blocks.n, dtype=np.int64)
        rank[np.argsort(-self.y, kind="stable")] = np.arange(self.blocks.n)
        counts, least, *_ = self.blocks.sums(CoverBounds, self.blocks.table, rank=rank, w=w / w.sum())
        return max(least, float((np.cumsum(counts) / np.arange(1, self.blocks.n + 1)).max()))

    def keep(self) -> EdgeValues:
        return self.state.keep()

    def close(self) -> None:
        self.state.close()
