"""Step-size strategies over an evaluator of trial steps.

``lanes(alphas)`` returns a Trial for each step size tried, all from one pass over the row vectors. A step is accepted
while the covering side's smoothed gain is at least the packing side's smoothed growth; their ratio never rises with
the step, so one crossing exists. A trial that covers all rows with an accepted step ends any search.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from poslp.config import SolveConfig


#: What the rounding of smoothed values of about one makes of a difference.
ROUNDING = 1e-14


@dataclass(frozen=True)
class Trial:
    alpha: float
    gain: float  # growth of the smoothed minimum of the covering rows
    growth: float  # growth of the smoothed maximum of the packing rows
    gain_slope: float
    growth_slope: float
    least_cover: float

    @property
    def accepted(self) -> bool:
        """gain >= growth, without dividing by a growth that may vanish. Both are differences of smoothed values near one,
        so what a rounding of those values can make of them is no refusal."""
        return self.gain - self.growth >= -max(ROUNDING, 1e-12 * max(abs(self.gain), abs(self.growth)))

    @property
    def linear_accepted(self) -> bool:
        return self.gain_slope >= self.growth_slope

    @property
    def ratio(self) -> float:
        return self.gain / self.growth if self.growth > 0 else float("inf")

    @property
    def finishes(self) -> bool:
        return self.accepted and self.least_cover >= 1


Lanes = Callable[[list[float]], list[Trial]]


class _Counted:
    def __init__(self, lanes: Lanes):
        self.lanes, self.evaluations, self.passes = lanes, 0, 0

    def __call__(self, alphas: list[float]) -> list[Trial]:
        self.evaluations += len(alphas)
        self.passes += 1
        return self.lanes(alphas)


def bracket(call: _Counted, first: float, cfg: SolveConfig, batched: bool) -> tuple[float, float | None, float | None]:
    """(finishing step, or the largest accepted and the least refused power of two times first). A refused first step
    leaves the bracket [first / 2, first]."""
    p = 0
    while True:
        tried = [first * 2.0**k for k in range(p, p + (cfg.most_doublings if batched else 1))]
        for t in call(tried):
            if t.finishes:
                return t.alpha, None, None
            if not t.accepted:
                return 0.0, t.alpha / 2, t.alpha
        p += len(tried)
        if p > 960:
            return tried[-1], None, None


def _evaluated(call: _Counted, cfg: SolveConfig, alpha_prev: float | None, batched: bool) -> tuple[float, float | None, float | None]:
    """The bracket from the previous step where warm, else from one; a warm start that is refused falls back to one."""
    if cfg.warm and alpha_prev and alpha_prev > 1:
        done, lo, hi = bracket(call, alpha_prev, cfg, batched)
        if lo is None or lo >= alpha_prev:
            return done, lo, hi
    return bracket(call, 1.0, cfg, batched)


def standard(call: _Counted, cfg: SolveConfig, _: float | None) -> float:
    return 1.0


def exponential(call: _Counted, cfg: SolveConfig, _: float | None) -> float:
    done, lo, _hi = bracket(call, 1.0, cfg, True)
    return done if lo is None else lo


def binary(call: _Counted, cfg: SolveConfig, alpha_prev: float | None) -> float:
    done, lo, hi = _evaluated(call, cfg, alpha_prev, False)
    if lo is None:
        return done
    while (hi - lo > (1 - cfg.eps) * lo) if cfg.stop == "loose" else (hi - lo > cfg.eps * lo):
        (t,) = call([(lo + hi) / 2])
        if t.finishes:
            return t.alpha
        lo, hi = (t.alpha, hi) if t.accepted else (lo, t.alpha)
    return lo


def kary(call: _Counted, cfg: SolveConfig, alpha_prev: float | None) -> float:
    done, lo, hi = bracket(call, 1.0, cfg, True)
    if lo is None:
        return done
    while hi - lo > cfg.eps * lo:
        for t in call([lo + (hi - lo) * k / (cfg.lanes + 1) for k in range(1, cfg.lanes + 1)]):
            if t.finishes:
                return t.alpha
            if not t.accepted:
                hi = t.alpha
                break
            lo = t.alpha
    return lo


def newton(call: _Counted, cfg: SolveConfig, alpha_prev: float | None) -> float:
    """Newton on ratio - 1, kept inside a bracket, then backed off by powers of 1 - eps until accepted."""
    alpha, lo, hi = (alpha_prev, 0.0, float("inf")) if cfg.warm and alpha_prev else (None, None, None)
    if alpha is None:
        done, lo, hi = bracket(call, 1.0, cfg, True)
        if lo is None:
            return done
        alpha = lo
    for _ in range(10):
        (t,) = call([alpha])
        if t.finishes:
            return t.alpha
        lo, hi = (max(lo, alpha), hi) if t.accepted else (lo, min(hi, alpha))
        slope = (t.gain_slope * t.growth - t.gain * t.growth_slope) / t.growth**2 if t.growth > 0 else 0.0
        ahead = alpha - (t.ratio - 1) / slope if slope < 0 else 2 * alpha
        ahead = min(ahead, 4 * alpha)
        if not lo < ahead < hi:
            ahead = (lo + hi) / 2 if hi < float("inf") else 2 * alpha
        if abs(ahead - alpha) <= cfg.eps * alpha:
            alpha = ahead
            break
        alpha = ahead
    while alpha >= 1e-9:
        tried = [alpha * (1 - cfg.backoff * cfg.eps) ** k for k in range(16)]
        # a step of one is tried before any below it: only its refusal tells of infeasibility
        if alpha >= 1 > tried[-1]:
            tried = [a for a in tried if a > 1] + [1.0] + [a for a in tried if a < 1]
        for t in call(tried):
            if t.accepted:
                return t.alpha
        alpha *= (1 - cfg.backoff * cfg.eps) ** 16
    return 0.0


def first_order(call: _Counted, cfg: SolveConfig, _: float | None) -> float:
    """The largest power of two whose slopes at the end still favour covering: by convexity an accepted step."""
    best, p = 0.5, 0
    while p <= 960:
        for t in call([2.0**k for k in range(p, p + cfg.most_doublings)]):
            if t.accepted and t.least_cover >= 1:
                return t.alpha
            if not t.linear_accepted:
                # slopes may refuse one where the step itself is accepted
                return 1.0 if t.alpha == 1 and t.accepted else best
            best = t.alpha
        p += cfg.most_doublings
    return best


STRATEGIES = {"standard": standard, "exponential": exponential, "binary": binary, "kary": kary, "newton": newton, "first_order": first_order}


def choose(lanes: Lanes, cfg: SolveConfig, alpha_prev: float | None) -> tuple[float, int, int]:
    """(alpha, evaluations, passes)."""
    call = _Counted(lanes)
    alpha = STRATEGIES[cfg.step](call, cfg, alpha_prev)
    return alpha, call.evaluations, call.passes
