"""The smoothed-potential solver: one loop for the local and the distributed engine.

A backend holds the vectors (x on variables, y = Px and dy on packing rows, z = Cx and dz on covering rows) and
answers with scalars; the loop, the step search and the target search run on those. Products are taken once per
iteration and side: the step search works on y + a dy and z + a dz.
"""

from __future__ import annotations

import math
import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace

import numpy as np

from poslp.config import SolveConfig, Status, eta
from poslp.plans.steps import Trial, choose


@dataclass
class Stats:
    max_y: float
    lse_y: float
    min_z: float
    lse_z: float
    sum_x: float


@dataclass
class Direction:
    max_d: float
    sum_d: float
    min_g: float
    max_h: float


@dataclass
class Outcome:
    status: Status
    iters: int
    trace: list[dict]
    lower: float = 0.0
    upper: float = math.inf
    best: float = 0.0
    x: object = None
    scale: float = 1.0
    max_violation: float = math.inf
    evaluations: int = 0
    runs: int = 1
    targets: list = field(default_factory=list)
    last: Stats | None = None


def _exp(x: np.ndarray) -> np.ndarray:
    """exp with a floor at e^-500, nothing in any sum, which keeps products clear of slow subnormal numbers."""
    return np.exp(np.maximum(x, -500.0))


class LocalBackend:
    """numpy vectors of one process. packing and covering have apply and apply_t; unit: the covering entries are all one."""

    unit, h, prices, progress = False, None, None, 0.0

    def __init__(self, packing, covering, unit: bool = False):
        self.p, self.c, self.unit = packing, covering, unit
        self.rows = packing.shape[0] + covering.shape[0]
        self.one_row = min(packing.shape[0], covering.shape[0]) == 1
        self.nnz = packing.nnz + covering.nnz

    def start(self, eps: float, x0: np.ndarray | None = None) -> None:
        n = self.p.shape[1]
        top = self.p.col_max()
        self.x = np.array(x0, dtype=float) if x0 is not None else np.where(top > 0, eps / (max(1, n) * np.where(top > 0, top, 1)), 1.0)
        self.y, self.z = self.p.apply(self.x), self.c.apply(self.x)
        self.active = np.ones(len(self.z), dtype=bool)

    def stats(self, eta_: float) -> Stats:
        z = self.z[self.active]
        my, mz = self.y.max(), z.min() if len(z) else math.inf
        ly = my + math.log(_exp(eta_ * (self.y - my)).sum()) / eta_
        lz = mz - math.log(_exp(-eta_ * (z - mz)).sum()) / eta_ if len(z) else math.inf
        return Stats(float(my), ly, float(self.z.min()), lz, float(self.x.sum()))

    def direction(self, eta_: float, s: Stats, scale: float) -> Direction:
        t = time.perf_counter()
        self.wp = _exp(eta_ * (self.y - s.lse_y))
        self.wc = np.where(self.active, _exp(-eta_ * (self.z - s.lse_z)), 0.0)
        v = time.perf_counter()
        g, h = self.p.apply_t(self.wp), self.c.apply_t(self.wc)
        self.h = h if self.p.shape[0] == 1 else None
        m = time.perf_counter()
        gain = np.where(h > 0, 1 - g / np.where(h > 0, h, 1), 0.0)
        self.d = np.maximum(0.0, gain) * self.x * scale / (2 * eta_)
        w = time.perf_counter()
        self.dy, self.dz = self.p.apply(self.d), self.c.apply(self.d)
        self.t_vec, self.t_matvec = v - t + w - m, m - v + time.perf_counter() - w
        return Direction(float(self.d.max()), float(self.d.sum()), float(g.min()), float(h.max()))

    def lanes(self, eta_: float, s: Stats, alphas: list[float]) -> list[Trial]:
        out = []
        dz, z = self.dz[self.active], self.z[self.active]
        for a in alphas:
            y, zz = self.y + a * self.dy, z + a * dz
            my, mz = y.max(), zz.min()
            ey, ez = _exp(eta_ * (y - my)), _exp(-eta_ * (zz - mz))
            growth = my + math.log(ey.sum()) / eta_ - s.lse_y
            gain = mz - math.log(ez.sum()) / eta_ - s.lse_z
            out.append(Trial(a, gain, growth, float(ez @ dz / ez.sum()), float(ey @ self.dy / ey.sum()), float((self.z + a * self.dz).min())))
        return out

    def advance(self, alpha: float) -> None:
        self._average(alpha * float(self.d.sum()))
        self.x = self.x + alpha * self.d
        self.y = self.y + alpha * self.dy
        self.z = self.z + alpha * self.dz

    def _average(self, progress: float) -> None:
        """Covering prices, averaged by the objective that each iteration adds."""
        if self.h is not None:
            self.prices = progress * self.h + (0 if self.prices is None else self.prices)
            self.progress += progress

    def average_bound(self) -> float:
        """Averages of weights are weights, so their prices bound a covering optimum from below as any others do."""
        return self.progress / float(self.prices.max()) if self.prices is not None and self.prices.max() > 0 else 0.0

    def capped(self, least: float) -> np.ndarray | None:
        """A cover's values beyond one do nothing where all entries are zero or one."""
        return np.minimum(1.0, self.x / least) if self.unit else None

    def drop(self) -> int:
        self.active &= self.z < 1
        return int(self.active.sum())

    def keep(self, x: np.ndarray | None = None):
        return self.x.copy() if x is None else x


def solve_feasibility(backend, cfg: SolveConfig, kind: str = "mixed", enough=None, x0=None) -> Outcome:
    """Is there x >= 0 with Px <= 1 and Cx >= 1? kind: mixed, packing (the covering side is the objective row) or
    covering (the packing side is). enough(lower, upper) may end a pure problem early, on its certificate."""
    eps = cfg.inner()
    eta_ = eta(backend.rows, eps)
    backend.start(eps, x0) if x0 is not None else backend.start(eps)
    out = Outcome(Status.ITER_LIMIT, 0, [])
    alpha = None
    scale = 2.0 if backend.one_row else 1.0
    s = backend.stats(eta_)
    for k in range(cfg.max_iter + 1):
        _certify(backend, s, kind, out)
        if s.min_z >= 1:
            # the potential starts at 1.2 eps at most and never grows, unless a start was given
            fits = kind != "mixed" or s.max_y <= (1 + 1.2 * eps) * s.min_z * (1 + 1e-9)
            out.status = Status.FEASIBLE if fits else Status.ITER_LIMIT
            break
        if k == cfg.max_iter:
            break
        d = backend.direction(eta_, s, scale)
        if kind == "packing" and d.min_g > 0:
            out.upper = min(out.upper, 1 / d.min_g)
        if kind == "covering" and d.max_h > 0:
            out.lower = max(out.lower, 1 / d.max_h, backend.average_bound() if hasattr(backend, "average_bound") else 0.0)
        if d.max_d <= 0:
            out.status = Status.INFEASIBLE_DIRECTION
            break
        if enough and enough(out.lower, out.upper):
            out.status = Status.CERTIFIED
            break
        t = time.perf_counter()
        alpha, evaluations, passes = choose(lambda a, s=s: backend.lanes(eta_, s, a), cfg, alpha)
        searched = time.perf_counter() - t
        if alpha < 1:
            out.status = Status.INFEASIBLE_STEP
            break
        backend.advance(alpha)
        out.iters += 1
        out.evaluations += evaluations
        before, s = s, backend.stats(eta_)
        out.trace.append({"iter": k + 1, "alpha": alpha, "step_iters": evaluations, "passes": passes, "max_px": s.max_y, "min_cx": s.min_z, "potential": s.lse_y - s.lse_z, "potential_before": before.lse_y - before.lse_z,
                          "max_violation": max(0.0, s.max_y - 1, 1 - s.min_z), "objective": s.sum_x, "lower": out.lower, "upper": out.upper, "t_matvec": getattr(backend, "t_matvec", 0.0), "t_vec": getattr(backend, "t_vec", 0.0), "t_search": searched})
        if cfg.drop_satisfied and s.min_z < 1:
            backend.drop()
            s = backend.stats(eta_)
    if out.x is None:
        out.x, out.scale = backend.keep(), 1.0
    if kind == "mixed" and s.min_z > 0:
        over = max(1.0, s.min_z)
        out.x, out.scale = backend.keep(), 1 / over
        out.max_violation = max(0.0, s.max_y / over - 1, 1 - s.min_z / over)
    out.last = s
    if hasattr(backend, "close"):
        backend.close()
    return out


def release(x) -> None:
    """Frees what an outcome's point holds, once another one has taken its place."""
    if hasattr(x, "release"):
        x.release()


def _certify(backend, s: Stats, kind: str, out: Outcome) -> None:
    """Keeps the best scaled iterate of a pure problem: a feasible point and so a bound on the optimum."""
    if kind == "packing" and s.max_y > 0:
        value = s.sum_x / s.max_y
        if value > out.lower:
            out.lower, out.best, out.scale, out.x, out.max_violation = value, value, 1 / s.max_y, backend.keep(), 0.0
    if kind == "covering" and s.min_z > 0:
        capped = backend.capped(s.min_z) if hasattr(backend, "capped") else None
        value = s.sum_x / s.min_z if capped is None else float(capped.sum())
        if value < out.upper:
            out.upper, out.best, out.max_violation = value, value, 0.0
            out.x, out.scale = (backend.keep(), 1 / s.min_z) if capped is None else (backend.keep(capped), 1.0)


#: A search ends open once its runs would need an accuracy so many times finer than its own.
MOST_ACCURACY = 256


def search_target(solve, lo: float, hi: float, eps: float, kind: str, most: int = 40, lanes: int = 1, point: Outcome | None = None) -> Outcome:
    """Bisection over the target of a pure problem, steered by certificates: ends when upper <= (1 + eps) lower.
    solve(target, enough, eps) runs one feasibility problem. The bracket moves by primal and dual values alone, never by a
    run's status. A run that leaves it as it was is followed by one of half its accuracy. lanes: targets tried side by
    side, at equal ratios inside the bracket. point: a feasible point to begin with, by its best, x and scale."""
    best = point
    lower, upper, iters, trace, targets, evaluations = lo, hi, 0, [], [], 0
    x, scale, inner = None, None, eps
    value = lo if kind == "packing" else hi
    if point is not None:
        x, scale, value = point.x, point.scale, point.best

    def enough(a: float, b: float) -> bool:
        return min(b, upper) <= (1 + eps) * max(a, lower) and ((kind == "packing" and a * (1 + eps) >= min(b, upper)) or (kind == "covering" and b <= (1 + eps) * max(a, lower)))

    def closed() -> bool:
        """The point itself is near enough, not only the bracket, whose ends may be bounds that no point stands for."""
        return x is not None and (upper <= (1 + eps) * value * (1 + 1e-12) if kind == "packing" else value <= (1 + eps) * lower * (1 + 1e-12))

    for _ in range(most):
        if closed():
            break
        low = lower if lower > 0 else upper / 4
        tried = [low * (upper / low) ** (k / (lanes + 1)) for k in range(1, lanes + 1)]
        if (1 + eps / 4) * upper <= (1 + eps) * lower:
            # what is left is to find a point: at a target that can be met, and whose points are near enough to close
            tried, inner = [math.sqrt(lower * upper / (1 + eps)) if kind == "packing" else math.sqrt(upper * lower * (1 + eps))], min(inner, eps / 3)
        elif upper <= (1 + eps) * lower:
            inner = min(inner, eps / 3)  # little room: the middle of the bracket gives a near point, or a bound that makes room
        # the value found exceeds its target by up to the run's accuracy, so a narrow bracket needs half of it to close
        narrow = eps / 2 if upper <= (1 + 3 * eps) * lower else eps
        was = lower, upper
        run = lambda t, e=min(inner, narrow): solve(t, enough, e)
        if lanes == 1:
            done = [run(tried[0])]
        else:
            with ThreadPoolExecutor(lanes) as pool:
                done = list(pool.map(run, tried))
        for target, o in zip(tried, done):
            iters += o.iters
            evaluations += o.evaluations
            trace += [r | {"target": target} for r in o.trace]
            targets.append((target, str(o.status), o.iters))
            lower, upper = max(lower, o.lower), min(upper, o.upper)
            better = o.x is not None and o.best > 0 and (x is None or (o.best > value if kind == "packing" else o.best < value))
            release(x if better else o.x)
            if better:
                x, scale, value, best = o.x, o.scale, o.best, o
        if all(o.status == Status.ITER_LIMIT for o in done):
            break
        if (lower, upper) == was or upper > 0 and math.isclose(lower / upper, was[0] / was[1], rel_tol=5e-3):
            inner = min(inner, narrow) / 2
            if inner < eps / MOST_ACCURACY:
                break  # ITER_LIMIT: runs cost ever more
    done = closed()
    out = replace(best) if best else Outcome(Status.ITER_LIMIT, 0, [])
    out.status = Status.FEASIBLE if done else Status.ITER_LIMIT
    out.iters, out.trace, out.targets, out.evaluations, out.runs = iters, trace, targets, evaluations, len(targets)
    lower = min(lower, upper)  # a tight point's value may round to a little more than the bound; less is as true
    out.lower, out.upper, out.best, out.x, out.scale = lower, upper, value, x, scale
    return out
