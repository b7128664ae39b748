"""Generated graphs, seeded and made by Spark from a range of ids."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from poslp.sources.graphs import canonical


def _uniform(*cols) -> F.Column:
    """A number in [0, 1) from a hash of the columns: the same on every run and layout."""
    return F.pmod(F.xxhash64(*cols), F.lit(1 << 52)) / F.lit(float(1 << 52))


def rgg(spark: SparkSession, scale: int, seed: int = 1, degree: float = 7.5) -> DataFrame:
    """Points in the unit square, joined if nearer than a radius: a cell meets its neighbours only."""
    n = 1 << scale
    r = math.sqrt(2 * degree / n / math.pi) if n > 1 else 1.0
    cells = max(1, int(1 / r))
    p = spark.range(n).select("id", _uniform(F.lit(seed), F.lit(0), "id").alias("x"), _uniform(F.lit(seed), F.lit(1), "id").alias("y"))
    p = p.withColumns({"cx": F.floor(F.col("x") * cells), "cy": F.floor(F.col("y") * cells)})
    around = F.explode(F.array(*[F.struct((F.col("cx") + i).alias("cx"), (F.col("cy") + j).alias("cy")) for i in (-1, 0, 1) for j in (-1, 0, 1)]))
    q = p.select(F.col("id").alias("j"), F.col("x").alias("x2"), F.col("y").alias("y2"), around.alias("c")).select("j", "x2", "y2", "c.*")
    near = (F.col("x") - F.col("x2")) ** 2 + (F.col("y") - F.col("y2")) ** 2 <= r * r
    return p.join(q, ["cx", "cy"]).where((F.col("id") < F.col("j")) & near).select(F.col("id").alias("u"), F.col("j").alias("v"))


def kron(spark: SparkSession, scale: int, edge_factor: int = 40, seed: int = 1, weights=(0.57, 0.19, 0.19)) -> DataFrame:
    """Recursive quadrant sampling; repeats and loops are left out."""
    a, b, c = weights
    e = spark.range(edge_factor << scale)
    u = v = F.lit(0)
    for k in range(scale):
        t = _uniform(F.lit(seed), F.lit(k), "id")
        u = u * 2 + (t >= a + b).cast("long")
        v = v * 2 + (((t >= a) & (t < a + b)) | (t >= a + b + c)).cast("long")
    return canonical(e.select(u.alias("u"), v.alias("v")))


def grid(spark: SparkSession, rows: int, cols: int, drop: float = 0.1, seed: int = 1) -> DataFrame:
    """A lattice without a share of its edges."""
    p = spark.range(rows * cols)
    to = F.array(F.when((F.col("id") + 1) % cols != 0, F.col("id") + 1), F.when(F.col("id") + cols < rows * cols, F.col("id") + cols))
    e = p.select(F.col("id").alias("u"), F.explode(to).alias("v")).where(F.col("v").isNotNull())
    return e.where(_uniform(F.lit(seed), "u", "v") >= drop)


def complete(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("u"), F.explode(F.sequence(F.col("id"), F.lit(n - 1).cast("long"))).alias("v")).where(F.col("u") < F.col("v"))


def star(spark: SparkSession, leaves: int) -> DataFrame:
    return spark.range(1, leaves + 1).select(F.lit(0).cast("long").alias("u"), F.col("id").alias("v"))


def cycle(spark: SparkSession, n: int) -> DataFrame:
    return canonical(spark.range(n).select(F.col("id").alias("u"), ((F.col("id") + 1) % n).alias("v")))


def path(spark: SparkSession, edges: int) -> DataFrame:
    return spark.range(edges).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))


def complete_bipartite(spark: SparkSession, a: int, b: int) -> DataFrame:
    return canonical(spark.range(a).select((2 * F.col("id")).alias("u"), F.explode(F.sequence(F.lit(0), F.lit(b - 1))).alias("j")).select("u", (2 * F.col("j") + 1).alias("v")))


def random_binary(m: int, n: int, p: float, seed: int = 1):
    """An explicit 0/1 matrix without empty rows or columns."""
    from poslp.operators.matrices import Coo

    rng = np.random.default_rng(seed)
    a = rng.random((m, n)) < p
    a[np.arange(m), rng.integers(0, n, m)] = True
    a[rng.integers(0, m, n), np.arange(n)] = True
    r, c = np.nonzero(a)
    return Coo(r, c, np.ones(len(r)), (m, n))


def embedding_binary(spark: SparkSession, d: str, size: int, p: float):
    """An explicit 0/1 matrix of the first vectors that are finite and their first components: ones where a component is
    among the largest share p, and at the largest of each row and column."""
    from poslp.operators.matrices import Coo

    some = F.slice("embedding", 1, size)
    good = F.forall(some, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & (F.size(some) == size)
    rows = spark.read.parquet(f"{d}/embeddings.parquet").where(good).orderBy("vec_id").limit(size).select(some.alias("x")).collect()
    x = np.array([r["x"] for r in rows], dtype=float)
    if x.shape != (size, size):
        raise ValueError(f"the table has no {size} vectors of {size} components")
    a = x > np.quantile(x, 1 - p)
    a[np.arange(size), x.argmax(axis=1)] = True
    a[x.argmax(axis=0), np.arange(size)] = True
    r, c = np.nonzero(a)
    return Coo(r, c, np.ones(len(r)), (size, size))


def from_edge_file(spark: SparkSession, location: str, fmt: str = "mtx") -> DataFrame:
    """Edges of a coordinate file (mtx: comments that begin with %, one line of sizes, then entries), csv or parquet."""
    if fmt == "parquet":
        return canonical(spark.read.parquet(location))
    if fmt == "csv":
        return canonical(spark.read.schema("u long, v long").csv(location))
    lines = spark.read.text(location).select(F.trim("value").alias("line"), F.col("_metadata.file_path").alias("file"), F.monotonically_increasing_id().alias("at"))
    lines = lines.where(~F.col("line").startswith("%") & (F.col("line") != ""))
    # ids rise along a file's splits, so the first line of each file that is no comment holds its sizes
    sizes = lines.groupBy("file").agg(F.min("at").alias("at")).select("at")
    entries = lines.join(sizes, "at", "left_anti").select(F.split("line", r"\s+").alias("p"))
    return canonical(entries.select(F.col("p")[0].cast("long").alias("u"), F.col("p")[1].cast("long").alias("v")))
