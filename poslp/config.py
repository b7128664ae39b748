"""Settings and outcomes of a solve."""

from __future__ import annotations

import math
from dataclasses import dataclass
from enum import StrEnum


class Status(StrEnum):
    FEASIBLE = "FEASIBLE"
    INFEASIBLE_DIRECTION = "INFEASIBLE_DIRECTION"
    INFEASIBLE_STEP = "INFEASIBLE_STEP"
    ITER_LIMIT = "ITER_LIMIT"
    CERTIFIED = "CERTIFIED"


@dataclass(frozen=True)
class SolveConfig:
    eps: float = 0.1
    max_iter: int = 5000
    step: str = "kary"  # standard, exponential, binary, kary, newton, first_order
    stop: str = "relative"  # of the binary search: relative, loose
    warm: bool = True
    lanes: int = 16
    most_doublings: int = 24
    drop_satisfied: bool = False
    strict: bool = False
    bound: str = "tight"  # of the first upper target: tight, paper
    backoff: float = 1.0  # of the Newton step, as a multiple of eps
    engine: str = "spark"  # spark, or local: numpy in one process, for comparison
    layout: str = "auto"  # of the Spark engine: blocks, frames, or blocks up to vertex_bytes
    vertex_bytes: int = 64 << 20  # of one vertex vector, which the driver holds and broadcasts
    local_edges: int = 2_000_000  # the local engine refuses more
    checkpoint_every: int = 1
    early_certificate: bool = True
    target_lanes: int = 1  # targets of a pure problem tried side by side
    warm_targets: bool = False  # a target's run starts from the best point of the ones before

    def inner(self) -> float:
        """The accuracy inside the loop: the invariant is max(Px) <= min(Cx) + 1.2 eps."""
        return self.eps / 1.2 if self.strict else self.eps


def eta(rows: int, eps: float) -> float:
    return 10.0 * math.log(max(2, rows)) / eps
