"""Physical layouts of an edge table: a square grid of blocks, blocks of rows, or vertices broadcast to all."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poslp.functions.measures import shuffle_words

#: A vertex vector is broadcast up to so many bytes.
BROADCAST_BYTES = 64 << 20


@dataclass(frozen=True)
class Layout:
    kind: str
    blocks: int
    words: float


def grid2d(edges: DataFrame, blocks: int) -> DataFrame:
    """edges with the block of a square grid: a hub's edges spread over a whole row of it."""
    side = math.isqrt(blocks)
    key = F.pmod(F.xxhash64("u"), F.lit(side)) * side + F.pmod(F.xxhash64("v"), F.lit(side))
    return edges.withColumn("block", key).repartition(side * side, "block")


def row1d(edges: DataFrame, blocks: int) -> DataFrame:
    """edges in ranges of their first end, which keeps banded graphs together."""
    return edges.repartitionByRange(blocks, "u").withColumn("block", F.spark_partition_id())


def copies(placed: DataFrame) -> int:
    """Vertex values that a product sends to the blocks: the distinct ends in each."""
    return placed.select("block", F.explode(F.array("u", "v")).alias("vid")).distinct().count()


def product_by_block(placed: DataFrame, vector: DataFrame, col: str) -> DataFrame:
    """Sums over incident edges of values at the other end, block by block: vertex values are copied to the blocks that
    need them, edges stay, and each block sends one partial sum per vertex."""
    need = placed.select("block", F.explode(F.array("u", "v")).alias("vid")).distinct()
    sent = need.join(vector.select(F.col("row").alias("vid"), col), "vid")
    at_u = sent.select(F.col("block"), F.col("vid").alias("u"), F.col(col).alias("_u"))
    at_v = sent.select(F.col("block"), F.col("vid").alias("v"), F.col(col).alias("_v"))
    both = placed.join(at_u, ["block", "u"]).join(at_v, ["block", "v"])
    parts = both.select("block", F.explode(F.array(F.struct(F.col("u").alias("row"), F.col("_v").alias("x")), F.struct(F.col("v").alias("row"), F.col("_u").alias("x")))).alias("e"))
    return parts.groupBy("block", "e.row").agg(F.sum("e.x").alias("x")).groupBy("row").agg(F.sum("x").alias(col))


def choose(edges: DataFrame, blocks: int, lanes: int = 1, sample: float = 1.0) -> Layout:
    """The layout that moves least, by the copies counted on a sample of whole blocks' worth of edges."""
    n = edges.select(F.explode(F.array("u", "v")).alias("vid")).distinct().count()
    m = edges.count()
    if n * 8 * lanes <= BROADCAST_BYTES:
        return Layout("broadcast", blocks, float(n * blocks))
    part = edges.sample(sample, seed=7) if sample < 1 else edges
    options = [Layout("naive", blocks, shuffle_words(n, m, blocks, "naive")), Layout("grid2d", blocks, copies(grid2d(part, blocks)) / sample), Layout("row1d", blocks, copies(row1d(part, blocks)) / sample)]
    return min(options, key=lambda x: x.words)
