"""Relational tools, sinks and exact integer optima on the given tables."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from poslp import relational as rel
from poslp import workloads
from poslp.baselines.exact import brute_force, max_flow_density
from poslp.plans.shared import shared_dir
from poslp.queries import query, with_graph
from poslp.queries_more import _CLASSES, _classes
from poslp.sources import sinks
from poslp.sources.graphs import GRAPH_SQL, GRAPHS, STRONGEST_SQL, strongest_coorder, vertices

for _name in ("four_problems", "backoff_ablation", "coordinate_search"):
    query(_name)(getattr(workloads, _name))


@query("relational_grouping_sets", with_graph("customer_supplier", f"SELECT coalesce(c.side, 'all') AS side, coalesce(c.bin, -1)::BIGINT AS bin, count(*)::BIGINT AS n, sum(degree)::BIGINT AS total FROM {_CLASSES} c GROUP BY GROUPING SETS ((c.side), (c.bin), ())"))
def grouping_sets(spark, d):
    out = rel.sets_report(_classes(spark, d), [["side"], ["bin"], []], F.count(F.lit(1)).alias("n"), F.sum("degree").alias("total"))
    return out.select(F.coalesce("side", F.lit("all")).alias("side"), F.coalesce("bin", F.lit(-1)).alias("bin"), "n", "total")


@query("relational_unpivot_degrees", with_graph("customer_supplier", "SELECT vid, 'degree' AS measure, degree::BIGINT AS value FROM vt UNION ALL SELECT vid, 'twice', (2 * degree)::BIGINT FROM vt"))
def unpivot_degrees(spark, d):
    wide = vertices(GRAPHS["customer_supplier"](spark, d)).withColumn("twice", 2 * F.col("degree"))
    return rel.to_long(wide, ["vid"], ["degree", "twice"], "measure", "value")


@query("relational_intersect_support", f"(SELECT u, v FROM ({GRAPH_SQL['supplier_coorder']}) WHERE u % 2 = 0) INTERSECT (SELECT u, v FROM ({GRAPH_SQL['supplier_coorder']}) WHERE v % 3 = 0)")
def intersect_support(spark, d):
    e = GRAPHS["supplier_coorder"](spark, d)
    return rel.set_intersection(e.where(F.col("u") % 2 == 0), e.where(F.col("v") % 3 == 0)).select("u", "v")


@query("relational_salted_sum", with_graph("user_eventtype", "SELECT v AS key, sum(u)::BIGINT AS total FROM ed GROUP BY v"))
def salted_sum(spark, d):
    e = GRAPHS["user_eventtype"](spark, d).select(F.col("v").alias("key"), F.col("u").alias("total"))
    return rel.salted_sum(e, "key", "total")


@query("relational_observe_edges", with_graph("part_supplier", "SELECT count(*)::BIGINT AS n, max(u)::BIGINT AS top, (SELECT count(*)::BIGINT FROM vt WHERE vid % 2 = 0) AS n_left FROM ed"))
def observe_edges(spark, d):
    """The counters ride on the job that counts the left vertices."""
    e, seen = rel.observed(GRAPHS["part_supplier"](spark, d), F.count(F.lit(1)).alias("n"), F.max("u").alias("top"))
    n_left = e.select(F.explode(F.array("u", "v")).alias("vid")).where(F.col("vid") % 2 == 0).distinct().count()
    got = seen.get
    return spark.createDataFrame([(got["n"], got["top"], n_left)], "n long, top long, n_left long")


@query("relational_sketch_degrees", with_graph("customer_supplier", "SELECT count(*)::BIGINT AS n, true AS close FROM vt WHERE vid % 2 = 1"))
def sketch_degrees(spark, d):
    """Sketched against exact partners of each supplier: all within a tenth, five times the error asked for."""
    e = GRAPHS["customer_supplier"](spark, d).select(F.when(F.col("u") % 2 == 0, F.col("u")).otherwise(F.col("v")).alias("c"), F.when(F.col("u") % 2 == 0, F.col("v")).otherwise(F.col("u")).alias("s"))
    both = rel.sketched_degrees(e, "s", "c").join(e.groupBy("s").agg(F.count(F.lit(1)).alias("exact")), "s")
    return both.agg(F.count(F.lit(1)).alias("n"), F.every(F.abs(F.col("partners") - F.col("exact")) <= 0.1 * F.col("exact")).alias("close"))


@query("sink_partitioned_edges", " UNION ALL ".join(f"SELECT '{g}' AS graph, count(*)::BIGINT AS n, sum(u + v)::BIGINT AS total FROM ({GRAPH_SQL[g]})" for g in ("part_supplier", "order_part")))
def sink_partitioned_edges(spark, d):
    both = None
    for g in ("part_supplier", "order_part"):
        one = GRAPHS[g](spark, d).select(F.lit(g).alias("graph"), "u", "v")
        both = one if both is None else both.unionByName(one)
    back = sinks.write_partitioned(both, f"{shared_dir(spark)}/poslp/by-graph-{uuid.uuid4().hex}", "graph")
    return back.groupBy("graph").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("u") + F.col("v")).alias("total"))


@query("sink_bucketed_join", with_graph("part_supplier", "SELECT vid, degree, s::BIGINT AS partners FROM vt JOIN (SELECT u, sum(v) AS s FROM ed GROUP BY u) ON u = vid"))
def sink_bucketed_join(spark, d):
    """Edges and vertices in buckets by vertex: the join and the sum by vertex need no exchange."""
    edges, tag = GRAPHS["part_supplier"](spark, d), uuid.uuid4().hex
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    at = f"{shared_dir(spark)}/poslp/buckets-{tag}"
    e = sinks.write_bucketed(edges.select(F.col("u").alias("vid"), "v"), f"edges_{tag}", f"{at}-edges", "vid", n)
    t = sinks.write_bucketed(vertices(edges), f"vertices_{tag}", f"{at}-vertices", "vid", n)
    return t.join(e.hint("merge"), "vid").groupBy("vid", "degree").agg(F.sum("v").alias("partners"))


@query("densest_by_flow", with_graph("nation_region", "SELECT count(*)::BIGINT AS n_edges, round(max(degree) / (max(degree) + 1)::DOUBLE, 6) AS density FROM ed, (SELECT max(degree) AS degree FROM vt)"))
def densest_by_flow(spark, d):
    """Nations and regions are stars, the densest of which has the most leaves."""
    u, v, ids = workloads.local_graph(GRAPHS["nation_region"](spark, d))
    return spark.createDataFrame([(len(u), round(float(max_flow_density(u, v, len(ids))[0]), 6))], "n_edges long, density double")


_INTEGER = f"""WITH g AS ({STRONGEST_SQL}),
ids AS (SELECT vid, (row_number() OVER (ORDER BY vid) - 1)::INTEGER AS k FROM (SELECT u AS vid FROM g UNION SELECT v FROM g)),
e AS (SELECT (row_number() OVER (ORDER BY u, v) - 1)::INTEGER AS t, a.k AS i, b.k AS j FROM g JOIN ids a ON u = a.vid JOIN ids b ON v = b.vid),
s AS (SELECT unnest(range((1 << (SELECT count(*) FROM ids)::INTEGER)::BIGINT)) AS s),
r AS (SELECT unnest(range((1 << (SELECT count(*) FROM e)::INTEGER)::BIGINT)) AS s),
ends AS (SELECT k, bit_or((1 << t)::BIGINT) AS own, bit_or(((1 << i) | (1 << j))::BIGINT) AS near FROM ids JOIN e ON k = i OR k = j GROUP BY k),
inside AS (SELECT s, count(*) FILTER (WHERE (s >> i) & 1 = 1 AND (s >> j) & 1 = 1) AS held, count(*) FILTER (WHERE (s >> i) & 1 = 0 AND (s >> j) & 1 = 0) AS neither FROM s, e GROUP BY s)
SELECT 'matching' AS problem, max(bit_count(s))::DOUBLE AS optimum FROM r WHERE NOT EXISTS (SELECT 1 FROM ends WHERE bit_count(s & own) > 1)
UNION ALL SELECT 'vcover', min(bit_count(s))::DOUBLE FROM inside WHERE neither = 0
UNION ALL SELECT 'domset', min(bit_count(s))::DOUBLE FROM s WHERE NOT EXISTS (SELECT 1 FROM ends WHERE s & near = 0)
UNION ALL SELECT 'densest', max(held / bit_count(s)::DOUBLE) FROM inside WHERE s > 0"""


@query("integer_programs", _INTEGER)
def integer_programs(spark, d):
    """Optima by enumeration on the pairs of suppliers with the most common orders; the flow agrees on the density."""
    u, v, ids = workloads.local_graph(strongest_coorder(spark, d))
    rows = [(p, brute_force(p, u, v, len(ids))[0]) for p in ("matching", "vcover", "domset", "densest")]
    if float(max_flow_density(u, v, len(ids))[0]) != rows[-1][1]:
        raise RuntimeError("the densities by flow and by enumeration differ")
    return spark.createDataFrame(rows, "problem string, optimum double")
