"""Registered queries of the graph-LP engine and their DuckDB texts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bipartite matching of parts and suppliers end to end: one report row with its certificate."""
    from poslp.config import SolveConfig
    from poslp.plans.problems import solve
    from poslp.sources.graphs import part_supplier

    return solve("bimatching", part_supplier(spark, sf_dir), SolveConfig(), "part_supplier").report()


def queries() -> dict:
    from poslp import queries_lp, queries_more, queries_steps, queries_tools  # noqa: F401  register their queries
    from poslp.queries import QUERIES

    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    from poslp import queries_lp, queries_more, queries_steps, queries_tools  # noqa: F401
    from poslp.queries import SQL

    return dict(SQL)
