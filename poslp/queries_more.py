"""Relational queries around the methods, and the measured tables of the experiments."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from poslp import relational as rel
from poslp import workloads
from poslp.baselines.matching import greedy_matching
from poslp.plans.shared import materialise
from poslp.queries import query, with_graph
from poslp.sources.graphs import GRAPH_SQL, GRAPHS, table, vertices

for _name in ("run_times", "speedup_summary", "product_speedups", "violation_curves", "strategy_table", "breakdown_table", "layout_table", "exactness", "accuracy_sweep", "scaling_table"):
    query(_name)(getattr(workloads, _name))


@query("max_violation_start", f"SELECT round(greatest(0, 1 - min(0.05 / m * degree / greatest(1, degree // 4))), 6) AS max_violation FROM (SELECT vid, count(*) AS degree, sum(count(*)) OVER () / 2 AS m FROM (SELECT u AS vid FROM ({GRAPH_SQL['customer_part']}) UNION ALL SELECT v FROM ({GRAPH_SQL['customer_part']})) GROUP BY vid) WHERE vid % 2 = 0")
def max_violation_start(spark, d):
    """Of the uniform point 0.05 / m against the customers' lower bounds."""
    deg = vertices(GRAPHS["customer_part"](spark, d))
    m = deg.agg(F.sum("degree") / 2).first()[0]
    least = F.min(F.lit(0.05 / m) * F.col("degree") / F.greatest(F.lit(1), F.floor(F.col("degree") / 4)))
    return deg.where(F.col("vid") % 2 == 0).agg(F.round(F.greatest(F.lit(0.0), 1 - least), 6).alias("max_violation"))


def _classes(spark, d):
    deg = vertices(GRAPHS["customer_supplier"](spark, d))
    return deg.select(F.when(F.col("vid") % 2 == 0, "left").otherwise("right").alias("side"), (F.floor(F.col("degree") / 10) * 10).cast("long").alias("bin"), "degree")


_CLASSES = "(SELECT CASE WHEN vid % 2 = 0 THEN 'left' ELSE 'right' END AS side, (degree // 10 * 10)::BIGINT AS bin, degree FROM vt)"


@query("relational_rollup_degree", with_graph("customer_supplier", f"SELECT coalesce(c.side, 'all') AS side, coalesce(c.bin, -1)::BIGINT AS bin, count(*)::BIGINT AS n, sum(degree)::BIGINT AS total, grouping(c.side, c.bin)::BIGINT AS level FROM {_CLASSES} c GROUP BY ROLLUP (c.side, c.bin)"))
def rollup_degree(spark, d):
    out = rel.rollup_report(_classes(spark, d), ["side", "bin"], F.count(F.lit(1)).alias("n"), F.sum("degree").alias("total"))
    return out.select(F.coalesce("side", F.lit("all")).alias("side"), F.coalesce("bin", F.lit(-1)).alias("bin"), "n", "total", F.col("level").cast("long").alias("level"))


@query("relational_cube_edges", with_graph("customer_supplier", f"SELECT coalesce(c.side, 'all') AS side, coalesce(c.bin, -1)::BIGINT AS bin, count(*)::BIGINT AS n, grouping(c.side, c.bin)::BIGINT AS level FROM {_CLASSES} c GROUP BY CUBE (c.side, c.bin)"))
def cube_edges(spark, d):
    out = rel.cube_report(_classes(spark, d), ["side", "bin"], F.count(F.lit(1)).alias("n"))
    return out.select(F.coalesce("side", F.lit("all")).alias("side"), F.coalesce("bin", F.lit(-1)).alias("bin"), "n", F.col("level").cast("long").alias("level"))


@query("relational_window_rank_edges", "SELECT l_suppkey, l_partkey, q, rank::BIGINT AS rank FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY q DESC, l_partkey) AS rank FROM (SELECT l_suppkey, l_partkey, sum(l_quantity) AS q FROM lineitem GROUP BY 1, 2)) WHERE rank <= 3")
def window_rank_edges(spark, d):
    w = table(spark, d, "lineitem").groupBy("l_suppkey", "l_partkey").agg(F.sum("l_quantity").alias("q"))
    return rel.top_k(w, "l_suppkey", [F.desc("q"), F.col("l_partkey")], 3).withColumn("rank", F.col("rank").cast("long"))


@query("relational_semi_join_matched", with_graph("nation_region", "SELECT count(*)::BIGINT AS n_matched FROM (SELECT DISTINCT CASE WHEN u % 2 = 1 THEN u ELSE v END FROM ed)"))
def semi_join_matched(spark, d):
    e = GRAPHS["nation_region"](spark, d)
    ends = materialise(greedy_matching(e), "greedy").select(F.explode(F.array("u", "v")).alias("vid"))
    return rel.semi_matched(vertices(e).where(F.col("vid") % 2 == 1), ends, "vid").agg(F.count(F.lit(1)).alias("n_matched"))


@query("relational_anti_join_isolated", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def anti_join_isolated(spark, d):
    used = table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return rel.anti_isolated(table(spark, d, "customer").select("c_custkey"), used, "c_custkey")


@query("relational_union_rows", f"SELECT kind, count(*)::BIGINT AS n FROM (SELECT 'part' AS kind FROM ({GRAPH_SQL['part_supplier']}) UNION ALL SELECT 'customer' FROM ({GRAPH_SQL['customer_supplier']})) GROUP BY kind")
def union_rows(spark, d):
    both = GRAPHS["part_supplier"](spark, d).withColumn("kind", F.lit("part")).unionByName(GRAPHS["customer_supplier"](spark, d).withColumn("kind", F.lit("customer")))
    return both.groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


@query("relational_except_support", f"SELECT u, v FROM (({GRAPH_SQL['supplier_coorder']}) EXCEPT (SELECT u, v FROM ({GRAPH_SQL['supplier_coorder']}) WHERE (u + v) % 3 = 0))")
def except_support(spark, d):
    e = GRAPHS["supplier_coorder"](spark, d)
    return rel.set_difference(e, e.where((F.col("u") + F.col("v")) % 3 == 0)).select("u", "v")


@query("relational_pivot_degrees", with_graph("customer_supplier", f"SELECT bin, count(*) FILTER (WHERE side = 'left')::BIGINT AS \"left\", count(*) FILTER (WHERE side = 'right')::BIGINT AS \"right\" FROM {_CLASSES} GROUP BY bin"))
def pivot_degrees(spark, d):
    return _classes(spark, d).groupBy("bin").pivot("side", ["left", "right"]).agg(F.count(F.lit(1))).fillna(0, ["left", "right"])


@query("relational_session_events", "SELECT user_id, count(*)::BIGINT AS n_sessions, max(n)::BIGINT AS longest FROM (SELECT user_id, s, count(*) AS n FROM (SELECT user_id, sum(g) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS g FROM events)) GROUP BY 1, 2) GROUP BY user_id")
def session_events(spark, d):
    s = table(spark, d, "events").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return s.groupBy("user_id").agg(F.count(F.lit(1)).alias("n_sessions"), F.max("n").alias("longest"))


@query("relational_asof_events", "SELECT e.event_id, (SELECT round(arg_max(p.value, p.ts), 6) FROM events p WHERE p.event_type = 'purchase' AND p.user_id = e.user_id AND p.ts <= e.ts) AS last_value FROM events e WHERE e.event_type = 'click'")
def asof_events(spark, d):
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type", "value")
    left, right = e.where("event_type = 'click'").select("event_id", "user_id", "ts"), e.where("event_type = 'purchase'").select("user_id", "ts", "value")
    return rel.asof(left, right, "ts", "user_id", "value").select("event_id", F.round("last_value", 6).alias("last_value"))


@query("relational_interval_join", "SELECT count(*)::BIGINT AS n FROM events a JOIN events b ON abs(epoch(a.ts) - epoch(b.ts)) < 60 WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def interval_events(spark, d):
    e = table(spark, d, "events").select("event_id", "ts", "event_type")
    return rel.interval_join(e.where("event_type = 'click'"), e.where("event_type = 'purchase'"), "ts", 60).agg(F.count(F.lit(1)).alias("n"))


@query("relational_json_props", "SELECT (props::JSON ->> '$.k')::BIGINT AS k, count(*)::BIGINT AS n FROM events GROUP BY 1")
def json_props(spark, d):
    k = F.get_json_object("props", "$.k").cast("long")
    return table(spark, d, "events").groupBy(k.alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("relational_percentiles", with_graph("part_coorder", "SELECT quantile_disc(degree, 0.5)::BIGINT AS median, quantile_disc(degree, 0.9)::BIGINT AS p90 FROM vt"))
def percentiles(spark, d):
    deg = vertices(GRAPHS["part_coorder"](spark, d)).select("degree")
    n = deg.count()
    ranked = deg.groupBy("degree").agg(F.count(F.lit(1)).alias("n")).withColumn("upto", F.sum("n").over(Window.orderBy("degree")))
    at = lambda q: F.min(F.when(F.col("upto") >= F.lit(q * n), F.col("degree")))
    return ranked.agg(at(0.5).alias("median"), at(0.9).alias("p90"))
