from poslp.config import Status
from poslp.plans.solver import Outcome, search_target


def test_lower_never_passes_upper_by_rounding():
    point = Outcome(Status.FEASIBLE, 1, [], lower=10.000000000000027, upper=10.0, best=10.000000000000027, x=[1.0])
    out = search_target(lambda target, enough, eps: point, 5.0, 10.0, 0.1, "packing")
    assert out.status == Status.FEASIBLE and out.lower <= 10 <= out.upper
