"""Connected components of an edge table by alternating large and small stars.

Each half step is one aggregate with map-side combine and one join; both sides of the join are written tables, so
adaptive execution can split the partition of a hub. Nothing is collected but counts.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poslp.llm.common import materialise


def _star(edges: DataFrame, larger: bool) -> DataFrame:
    """Links each node's larger (or smaller, or equal) neighbours to the least node in sight."""
    if larger:
        seen = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    else:
        seen = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    seen = materialise(seen.distinct(), "star-edges")
    least = materialise(seen.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m")), "star-least")
    joined = seen.join(least, "a")
    if larger:
        out = joined.where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        out = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
    return out.where(F.col("a") != F.col("b")).distinct()


def connected_components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """edges: (a, b), any orientation, repeats and loops allowed. Returns (node, component), component the least node;
    only nodes with an edge to another node appear. Rows with a null end are left out."""
    now = edges.select("a", "b").where(F.col("a") != F.col("b"))
    state = None
    for _ in range(most_rounds):
        now = materialise(_star(_star(now, True), False), "star")
        r = now.agg(F.count(F.lit(1)), F.sum(F.hash("a", "b").cast("long")), F.sum(F.xxhash64("b", "a").cast("decimal(38,0)"))).first()
        if tuple(r) == state:
            return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
        state = tuple(r)
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")
