"""Graphs built from the given tables, in one normal form.

edges: (eid, u, v[, w]) with u < v, no repeats and no loops, eid the rank by (u, v) from 0. Two-sided graphs number a
left key 2k and a right key 2k + 1, so the sides never collide.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from poslp.sources.groups import Together


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def canonical(pairs: DataFrame, u: str = "u", v: str = "v") -> DataFrame:
    """(u, v) from any pairs: nulls and loops go, ends in order, each edge once."""
    pairs = pairs.select(F.col(u).cast("long").alias("_a"), F.col(v).cast("long").alias("_b"))
    return pairs.where(F.col("_a") != F.col("_b")).select(F.least("_a", "_b").alias("u"), F.greatest("_a", "_b").alias("v")).distinct()


def with_eid(edges: DataFrame) -> DataFrame:
    """Adds eid = rank by (u, v): ranks inside range partitions by u, shifted by the partitions' counts."""
    parts = edges.repartitionByRange("u", "v").withColumn("_p", F.spark_partition_id())
    parts = parts.withColumn("_k", F.row_number().over(Window.partitionBy("_p").orderBy("u", "v")))
    counts = parts.groupBy("_p").agg(F.count(F.lit(1)).alias("_n"), F.min(F.struct("u", "v")).alias("_from"))
    before = F.coalesce(F.sum("_n").over(Window.orderBy("_from").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    # one row a partition
    out = parts.join(F.broadcast(counts.select("_p", before.alias("_before"))), "_p")
    return out.select((F.col("_before") + F.col("_k") - 1).alias("eid"), *edges.columns)


def _sides(df: DataFrame, left: Column, right: Column) -> DataFrame:
    return df.select((2 * left.cast("long")).alias("u"), (2 * right.cast("long") + 1).alias("v")).where(F.col("u").isNotNull() & F.col("v").isNotNull())


def two_sided(df: DataFrame, left: Column, right: Column) -> DataFrame:
    """Left and right keys to canonical edges; left ends keep even numbers, whatever their order."""
    return canonical(_sides(df, left, right))


def nation_region(spark: SparkSession, d: str) -> DataFrame:
    return two_sided(table(spark, d, "nation"), F.col("n_nationkey"), F.col("n_regionkey"))


def customer_nation(spark: SparkSession, d: str) -> DataFrame:
    return two_sided(table(spark, d, "customer"), F.col("c_custkey"), F.col("c_nationkey"))


def order_customer(spark: SparkSession, d: str) -> DataFrame:
    return two_sided(table(spark, d, "orders"), F.col("o_orderkey"), F.col("o_custkey"))


def part_supplier(spark: SparkSession, d: str) -> DataFrame:
    return two_sided(table(spark, d, "lineitem"), F.col("l_partkey"), F.col("l_suppkey"))


def _bought(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity")
    return lines.join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))


def customer_part(spark: SparkSession, d: str) -> DataFrame:
    return two_sided(_bought(spark, d), F.col("o_custkey"), F.col("l_partkey"))


def customer_part_weighted(spark: SparkSession, d: str) -> DataFrame:
    """(u, v, w): w is the quantity bought."""
    rows = _bought(spark, d).select((2 * F.col("o_custkey")).alias("a"), (2 * F.col("l_partkey") + 1).alias("b"), F.col("l_quantity").cast("double").alias("q"))
    return rows.groupBy(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).agg(F.sum("q").alias("w"))


def customer_supplier(spark: SparkSession, d: str) -> DataFrame:
    return two_sided(_bought(spark, d), F.col("o_custkey"), F.col("l_suppkey"))


def order_part(spark: SparkSession, d: str) -> DataFrame:
    return two_sided(table(spark, d, "lineitem"), F.col("l_orderkey"), F.col("l_partkey"))


def shared(rows: DataFrame, key: str, item: str, least: int = 1) -> DataFrame:
    """Items that stand together under at least so many keys. An order holds few lines, which bounds the pairs."""
    one = rows.select(F.col(key).alias("k"), F.col(item).cast("long").alias("i")).distinct()
    other = one.select(F.col("k").alias("k2"), F.col("i").alias("j"))
    pairs = one.join(other, (F.col("k") == F.col("k2")) & (F.col("i") < F.col("j")))
    return pairs.groupBy(F.col("i").alias("u"), F.col("j").alias("v")).agg(F.count(F.lit(1)).alias("w")).where(F.col("w") >= least)


def part_coorder(spark: SparkSession, d: str) -> DataFrame:
    return shared(table(spark, d, "lineitem"), "l_orderkey", "l_partkey").select("u", "v")


def supplier_coorder(spark: SparkSession, d: str, least: int = 1) -> DataFrame:
    return shared(table(spark, d, "lineitem"), "l_orderkey", "l_suppkey", least).select("u", "v")


#: Edges of the small example graph, so that all subsets of its edges and vertices can be looked at.
EXAMPLE_EDGES = 7


def strongest_coorder(spark: SparkSession, d: str) -> DataFrame:
    """The pairs of suppliers that stand together in the most orders, ties to the lesser pair."""
    pairs = shared(table(spark, d, "lineitem"), "l_orderkey", "l_suppkey")
    return pairs.orderBy(F.desc("w"), "u", "v").limit(EXAMPLE_EDGES).select("u", "v")


def user_eventtype(spark: SparkSession, d: str) -> DataFrame:
    events = table(spark, d, "events").select("user_id", "event_type").distinct()
    # a handful of types
    types = events.select("event_type").distinct().select("event_type", F.row_number().over(Window.orderBy("event_type")).alias("t"))
    return two_sided(events.join(F.broadcast(types), "event_type"), F.col("user_id"), F.col("t"))


def users_together(spark: SparkSession, d: str) -> Together:
    """Users by the hour and type of their events; hundreds share one, so their pairs are not joined."""
    key = F.concat(F.col("event_type"), F.lit("|"), F.date_format(F.date_trunc("hour", "ts"), "yyyyMMddHH"))
    return Together(table(spark, d, "events"), key, F.col("user_id"))


def user_cooccur(spark: SparkSession, d: str) -> DataFrame:
    """Users with an event of one type in one hour."""
    return users_together(spark, d).pairs()


def embedding_knn(spark: SparkSession, d: str, k: int = 8, first: int | None = None) -> DataFrame:
    """Symmetric k nearest neighbours by cosine. The vectors are compared in blocks: one side is split into groups that
    fit a task, the other is streamed past them, and each group keeps its best k. Given first, the graph of so many vectors."""
    from poslp.operators.knn import block_knn

    rows = table(spark, d, "embeddings")
    if first is not None:
        rows = rows.orderBy("vec_id").limit(first)
    return canonical(block_knn(rows, "vec_id", "embedding", k), "a", "b")


def page_link(spark: SparkSession, d: str) -> DataFrame:
    """Pages and the addresses they link to; an address is numbered by its rank in order of value."""
    links = table(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href")).distinct()
    values = with_rank(links.select("href").distinct(), "href", "r")
    return two_sided(links.join(values, "href"), F.col("page_id"), F.col("r"))


def with_rank(values: DataFrame, col: str, name: str) -> DataFrame:
    """Rank from 1 of distinct values, without gathering them in one task."""
    parts = values.repartitionByRange(col).withColumn("_p", F.spark_partition_id())
    parts = parts.withColumn("_k", F.row_number().over(Window.partitionBy("_p").orderBy(col)))
    counts = parts.groupBy("_p").agg(F.count(F.lit(1)).alias("_n"), F.min(col).alias("_from"))
    before = F.coalesce(F.sum("_n").over(Window.orderBy("_from").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return parts.join(F.broadcast(counts.select("_p", before.alias("_before"))), "_p").select(col, (F.col("_before") + F.col("_k")).alias(name))


def doc_overlap(spark: SparkSession, d: str, min_jaccard: float = 0.8, shingle: int = 5) -> DataFrame:
    """Documents whose sets of word shingles overlap, found through shared rare shingles (prefix filtering)."""
    words = F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(r"\S+"), F.lit(0))
    rows = table(spark, d, "documents").select("doc_id", words.alias("w"))
    grams = F.transform(F.sequence(F.lit(0), F.size("w") - shingle), lambda i: F.xxhash64(F.array_join(F.slice("w", i + 1, shingle), " ")))
    rows = rows.where(F.size("w") >= shingle).select("doc_id", F.sort_array(F.array_distinct(grams)).alias("g"))
    n = F.size("g")
    head = rows.select("doc_id", "g", F.explode(F.slice("g", 1, (n - F.ceil(n * min_jaccard) + 1).cast("int"))).alias("k"))
    other = head.select(F.col("doc_id").alias("d2"), F.col("g").alias("g2"), F.col("k"))
    pairs = head.join(other, "k").where(F.col("doc_id") < F.col("d2")).dropDuplicates(["doc_id", "d2"])
    both = F.size(F.array_intersect("g", "g2"))
    return pairs.where(both / (F.size("g") + F.size("g2") - both) >= min_jaccard).select(F.col("doc_id").alias("u"), F.col("d2").alias("v"))


def vertices(edges: DataFrame) -> DataFrame:
    """(vid, degree)."""
    return edges.select(F.explode(F.array("u", "v")).alias("vid")).groupBy("vid").agg(F.count(F.lit(1)).alias("degree"))


GRAPHS = {
    "nation_region": nation_region, "customer_nation": customer_nation, "order_customer": order_customer, "part_supplier": part_supplier, "customer_part": customer_part,
    "customer_supplier": customer_supplier, "order_part": order_part, "part_coorder": part_coorder, "supplier_coorder": supplier_coorder,
    "user_eventtype": user_eventtype, "user_cooccur": user_cooccur, "page_link": page_link,
}

#: Graphs whose pairs stand under few and large keys: numbered edges and degrees without a shuffle of pairs.
TOGETHER = {"user_cooccur": users_together}


def numbered(spark: SparkSession, d: str, graph: str) -> DataFrame:
    """(eid, u, v) of a graph."""
    return TOGETHER[graph](spark, d).numbered() if graph in TOGETHER else with_eid(GRAPHS[graph](spark, d))


def degrees(spark: SparkSession, d: str, graph: str) -> DataFrame:
    """(vid, degree) of a graph."""
    return TOGETHER[graph](spark, d).degrees() if graph in TOGETHER else vertices(GRAPHS[graph](spark, d))


_BOUGHT = "lineitem JOIN orders ON l_orderkey = o_orderkey"


def _two(left: str, right: str, source: str) -> str:
    return f"SELECT DISTINCT least(2*{left}, 2*{right}+1)::BIGINT AS u, greatest(2*{left}, 2*{right}+1)::BIGINT AS v FROM {source} WHERE {left} IS NOT NULL AND {right} IS NOT NULL"


def _together(key: str, item: str, source: str, least: int = 1) -> str:
    return f"SELECT a.i::BIGINT AS u, b.i::BIGINT AS v FROM (SELECT DISTINCT {key} AS k, {item} AS i FROM {source}) a JOIN (SELECT DISTINCT {key} AS k, {item} AS i FROM {source}) b ON a.k = b.k AND a.i < b.i GROUP BY 1, 2 HAVING count(*) >= {least}"


STRONGEST_SQL = f"SELECT u, v FROM ({_together('l_orderkey', 'l_suppkey', 'lineitem').replace('::BIGINT AS v FROM', '::BIGINT AS v, count(*) AS w FROM', 1)}) ORDER BY w DESC, u, v LIMIT {EXAMPLE_EDGES}"

#: The same graphs in DuckDB's SQL, each a query of (u, v).
GRAPH_SQL = {
    "nation_region": _two("n_nationkey", "n_regionkey", "nation"),
    "customer_nation": _two("c_custkey", "c_nationkey", "customer"),
    "order_customer": _two("o_orderkey", "o_custkey", "orders"),
    "part_supplier": _two("l_partkey", "l_suppkey", "lineitem"),
    "customer_part": _two("o_custkey", "l_partkey", _BOUGHT),
    "customer_supplier": _two("o_custkey", "l_suppkey", _BOUGHT),
    "order_part": _two("l_orderkey", "l_partkey", "lineitem"),
    "part_coorder": _together("l_orderkey", "l_partkey", "lineitem"),
    "supplier_coorder": _together("l_orderkey", "l_suppkey", "lineitem"),
    "user_eventtype": _two("user_id", "t", "(SELECT user_id, dense_rank() OVER (ORDER BY event_type) AS t FROM events)"),
    "user_cooccur": _together("event_type || date_trunc('hour', ts)::VARCHAR", "user_id", "events"),
    "page_link": _two("page_id", "r", "(SELECT page_id, dense_rank() OVER (ORDER BY href) AS r FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages))"),
}
