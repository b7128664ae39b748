import pytest

from poslp import registry

QUERIES, SQL = registry.queries(), registry.oracle_sql()
#: Distributed solves take the longest; the driver compares all of them.
SLOW = {"densest_star", "generalized_matching", "greedy_matching", "standard_step_trace", "graph_profile", "domset_star", "vcover_star"}


@pytest.mark.parametrize("name", [k for k in QUERIES if k in SQL and k not in SLOW])
def test_query_equals_its_sql(name, same):
    same(QUERIES[name], SQL[name])


def test_flagship(spark, data):
    row = registry.flagship(spark, data).first()
    assert row["status"] == "FEASIBLE" and row["lower"] <= 10 <= row["upper"] * (1 + 1e-9)
