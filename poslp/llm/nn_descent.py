"""Approximate nearest neighbours: a neighbour graph by NN-descent, searched greedily.

Equal vectors collapse to one node before anything else, so copies cost nothing and cannot crowd a neighbourhood.
The graph starts from the best neighbours inside random blocks (two hashings of the nodes into blocks of about a
thousand). Each round joins neighbours of neighbours: both directions of the sampled fresh and old edges meet at
their centre with the members' vectors, every pair with a fresh edge is compared, and pairs nearer than a member's
furthest neighbour are merged into its list. A neighbourhood has at most four samples of ``sample`` members, whatever
the in-degree of a hub. Rounds end when few edges are fresh. All comparisons are double-precision distances of
the original vectors.

A query starts at its own node if it is a row of the index, else at ``ENTRIES`` fixed nodes, and keeps a beam of the
nearest nodes seen; each round expands all beam nodes not yet expanded, until none is left. All queries advance
together as joins. Steps are written tables; nothing but counts reaches the driver.

The sampling of edges is part of NN-descent and bounds work, not results: every row is indexed, every query answered.
Recall against brute force is tested (at least 0.9).

Defined results: vectors that are null, zero, hold null or non-finite components, or have another length than the
largest usual one (the most frequent length, the longer on ties) take no part, neither as queries nor as candidates;
repeated rows of an id count once; an empty table gives an empty table; only the id and vector columns are read.
"""

from __future__ import annotations

import gc
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from poslp.llm.common import materialise, table

NEIGHBOURS = 28
SAMPLE = 14
ROUNDS = 6
BLOCK = 1000
BEAM = 256
ENTRIES = 64
EDGE = "u long, v long, d double, fresh boolean"


def _vectors(column: pa.Array) -> np.ndarray:
    """The rows of an array column without nulls, in double precision."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 1)


def _squares(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.maximum((x**2).sum(1)[:, None] + (y**2).sum(1)[None, :] - 2 * x @ y.T, 0)


def _batch(names: list[str], *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=names)


def _in_block(keep: int):
    def run(block: pa.Table) -> pa.Table:
        ids, x = block.column("id").to_numpy(), _vectors(block.column("code"))
        u, v, d = [], [], []
        if len(ids) > 1:
            near = _squares(x, x)
            np.fill_diagonal(near, np.inf)
            k = min(keep, len(ids) - 1)
            best = np.argpartition(near, k - 1, axis=1)[:, :k]
            u, v, d = np.repeat(ids, k), ids[best].ravel(), np.take_along_axis(near, best, 1).ravel()
        return pa.table({"u": pa.array(u, pa.int64()), "v": pa.array(v, pa.int64()), "d": pa.array(d, pa.float64()), "fresh": pa.array(np.ones(len(u), dtype=bool))})

    return run


def _local_join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs of each neighbourhood (at least one of them fresh) that are nearer than a member's furthest neighbour."""
    for batch in batches:
        lists = batch.column(0)
        at, flat = lists.offsets.to_numpy(), lists.values
        ids, furthest, fresh = (flat.field(k).to_numpy(zero_copy_only=False) for k in ("m", "furthest", "fresh"))
        x = _vectors(flat.field("code"))
        u, v, d = [], [], []
        for s, e in zip(at[:-1], at[1:]):
            m, f, y = ids[s:e], fresh[s:e], x[s:e]
            near = _squares(y, y)
            a, b = np.nonzero((f[:, None] | f[None, :]) & (near < furthest[s:e, None]) & (m[:, None] != m[None, :]))
            u.append(m[a])
            v.append(m[b])
            d.append(near[a, b])
        if u:
            u, v, d = np.concatenate(u), np.concatenate(v), np.concatenate(d)
            yield _batch(["u", "v", "d", "fresh"], u, v, d, np.ones(len(u), dtype=bool))


def _distances(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if batch.num_rows:
            yield _batch(["qid", "v", "d"], batch.column(0), batch.column(1), ((_vectors(batch.column(2)) - _vectors(batch.column(3))) ** 2).sum(1))


def _nearest(edges: DataFrame, keep: int) -> DataFrame:
    """Each node's nearest edges, a pair once (as an old edge if it was there): one exchange for both windows."""
    once = Window.partitionBy("u", "v").orderBy("fresh", "d")
    by_node = Window.partitionBy("u").orderBy("d", "v")
    edges = edges.repartition("u").withColumn("_o", F.row_number().over(once)).where(F.col("_o") == 1)
    return edges.withColumn("_r", F.row_number().over(by_node)).where(F.col("_r") <= keep).select("u", "v", "d", "fresh")


def _release(spark: SparkSession) -> None:
    """Lets Spark's cleaner delete the shuffle files of steps that are done."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def usable(rows: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(id, vec): vec array<double>, of the rows that take part."""
    vec = F.col(vector_col).cast("array<double>")
    plain = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))
    rows = rows.select(F.col(id_col).cast("long").alias("id"), vec.alias("vec")).where(F.col("id").isNotNull() & F.col("vec").isNotNull())
    rows = rows.where(F.forall("vec", plain) & F.exists("vec", lambda x: x != 0))
    usual = rows.groupBy(F.size("vec").alias("n")).count().orderBy(F.desc("count"), F.desc("n")).first()
    return rows.where(F.size("vec") == F.lit(usual["n"] if usual else 0))


class NeighbourGraph:
    """nodes: (id, vec, code), one row a distinct vector, code the vector in the width it came in; members: (node, id), the copies; edges: (u, v, d)."""

    def __init__(self, rows: DataFrame, id_col: str, vector_col: str, neighbours: int = NEIGHBOURS, sample: int = SAMPLE, rounds: int = ROUNDS):
        self.spark = rows.sparkSession
        wide = rows.schema[vector_col].dataType
        rows = materialise(usable(rows, id_col, vector_col), "vectors")
        # without loss: four bytes a component where the table holds no more
        kind = "array<float>" if wide.simpleString() == "array<float>" else "array<double>"
        self.nodes = materialise(rows.groupBy("vec").agg(F.min("id").alias("id")).select("id", "vec", F.col("vec").cast(kind).alias("code")), "nodes")
        self.rows = rows
        self.count = self.nodes.count()
        self.edges = self._build(neighbours, sample, rounds)

    def _build(self, keep: int, sample: int, rounds: int) -> DataFrame:
        slim = self.nodes.select("id", "code")
        blocks = max(1, -(-self.count // BLOCK))
        seeded = slim.withColumn("_seed", F.explode(F.array(*[F.lit(s) for s in range(1 if blocks == 1 else 2)])))
        seeded = seeded.withColumn("_block", F.pmod(F.xxhash64("_seed", "id"), F.lit(blocks)))
        edges = materialise(_nearest(seeded.groupBy("_seed", "_block").applyInArrow(_in_block(keep), EDGE), keep), "graph")
        for k in range(rounds if blocks > 1 else 0):
            edges = self._round(slim, edges, keep, sample, k)
            _release(self.spark)
            if edges.where("fresh").count() < 0.05 * keep * self.count:
                break
        return edges.select("u", "v", "d")

    def _round(self, slim: DataFrame, edges: DataFrame, keep: int, sample: int, k: int) -> DataFrame:
        lot = F.xxhash64(F.lit(k), "u", "v")
        furthest = edges.groupBy(F.col("u").alias("m")).agg(F.when(F.count(F.lit(1)) >= keep, F.max("d")).otherwise(F.lit(float("inf"))).alias("furthest"))
        member = materialise(slim.withColumnRenamed("id", "m").join(furthest, "m", "left").fillna(float("inf"), ["furthest"]), "members")
        drawn = Window.partitionBy("u", "fresh").orderBy(lot)
        out = edges.withColumn("_r", F.row_number().over(drawn)).withColumn("_drawn", F.col("_r") <= sample).drop("_r")
        out = materialise(out, "drawn")
        chosen = out.where("_drawn")
        back = chosen.select(F.col("v").alias("c"), F.col("u").alias("m"), "fresh", F.xxhash64(F.lit(k), "v", "u").alias("_lot"))
        back = back.withColumn("_r", F.row_number().over(Window.partitionBy("c", "fresh").orderBy("_lot"))).where(F.col("_r") <= sample)
        near = chosen.select(F.col("u").alias("c"), F.col("v").alias("m"), "fresh").unionByName(back.select("c", "m", "fresh"))
        met = near.join(member, "m").groupBy("c").agg(F.collect_list(F.struct("m", "code", "furthest", "fresh")).alias("of"))
        pairs = met.select("of").mapInArrow(_local_join, EDGE)
        kept = out.select("u", "v", "d", (F.col("fresh") & ~F.col("_drawn")).alias("fresh"))
        return materialise(_nearest(kept.unionByName(pairs), keep), "graph")

    def search(self, queries: DataFrame, id_col: str, vector_col: str, k: int = 10, beam: int = BEAM, most_rounds: int = 20) -> DataFrame:
        """(query_id, rank, vec_id, score): the k nearest rows found for each query, but for the row of its own id."""
        ask = usable(queries, id_col, vector_col).join(self.nodes.select("vec", F.col("id").alias("node")), "vec", "left")
        ask = materialise(ask.dropDuplicates(["id"]).select(F.col("id").alias("qid"), F.col("vec").alias("qvec"), "node"), "queries")
        slim = self.nodes.select(F.col("id").alias("v"), "code")
        ways = self.edges.unionByName(self.edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "d"))
        back = ways.withColumn("_r", F.row_number().over(Window.partitionBy("u").orderBy("d", "v"))).where(F.col("_r") <= 2 * NEIGHBOURS)
        ways = materialise(back.select("u", "v").distinct(), "ways")
        start = ask.where(F.col("node").isNotNull()).select("qid", F.col("node").alias("v"))
        if ask.where(F.col("node").isNull()).limit(1).count():
            doors = slim.orderBy(F.xxhash64("v")).limit(ENTRIES).select("v")
            start = start.unionByName(ask.where(F.col("node").isNull()).select("qid").join(F.broadcast(doors)))  # at most ENTRIES rows
        state = materialise(self._beam(self._measured(start, ask, slim).withColumn("done", F.lit(False)), beam), "beam")
        for _ in range(most_rounds):
            front = state.where(~F.col("done"))
            if not front.limit(1).count():
                break
            seen = front.select("qid", F.col("v").alias("u")).join(ways, "u").select("qid", "v").distinct()
            new = self._measured(seen, ask, slim).withColumn("done", F.lit(False))
            state = materialise(self._beam(state.withColumn("done", F.lit(True)).unionByName(new), beam), "beam")
            _release(self.spark)
        return self._ranked(state, ask, k)

    def _measured(self, pairs: DataFrame, ask: DataFrame, slim: DataFrame) -> DataFrame:
        both = pairs.join(slim, "v").join(ask.select("qid", "qvec"), "qid")
        return both.select("qid", "v", "code", "qvec").mapInArrow(_distances, "qid long, v long, d double")

    def _beam(self, found: DataFrame, beam: int) -> DataFrame:
        once = Window.partitionBy("qid", "v").orderBy(F.desc("done"))
        found = found.repartition("qid").withColumn("_o", F.row_number().over(once)).where(F.col("_o") == 1)
        best = Window.partitionBy("qid").orderBy("d", "v")
        return found.withColumn("_r", F.row_number().over(best)).where(F.col("_r") <= beam).select("qid", "v", "d", "done")

    def _ranked(self, state: DataFrame, ask: DataFrame, k: int) -> DataFrame:
        exact = state.select("qid", "v").join(self.nodes.select(F.col("id").alias("v"), "vec"), "v").join(ask.select("qid", "qvec"), "qid")
        exact = exact.select("qid", "v", euclidean(F.col("vec"), F.col("qvec")).alias("score"))
        # a query leaves out at most its own row, so the k + 1 least ids of a node suffice
        held = self.rows.select("id", "vec").dropDuplicates(["id"]).join(self.nodes.select("vec", F.col("id").alias("v")), "vec")
        held = held.withColumn("_r", F.row_number().over(Window.partitionBy("v").orderBy("id"))).where(F.col("_r") <= k + 1)
        rows = exact.join(held.select("v", "id"), "v").where(F.col("id") != F.col("qid"))
        rank = F.row_number().over(Window.partitionBy("qid").orderBy("score", "id")).cast("int")
        return rows.withColumn("rank", rank).where(F.col("rank") <= k).select(F.col("qid").alias("query_id"), "rank", F.col("id").alias("vec_id"), "score")


def euclidean(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))


def op1_nn_descent(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    graph = NeighbourGraph(rows, "vec_id", "embedding")
    return graph.search(rows.where(F.col("vec_id") % 100 == 0), "vec_id", "embedding")
