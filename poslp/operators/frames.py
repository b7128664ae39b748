"""Matrix-free operators over DataFrames.

Variables stand in a frame with a key ``var`` and whatever structure the operator needs (an edge's ends, for one);
rows stand in a frame with a key ``row``. ``forward`` sums columns of variables into rows, ``back`` brings a column of
rows to the variables. Sums by key combine on the map side, so a hub sends one partial sum per task; lookups are
joins on the vertex key, broadcast by Spark only while the vertex table is under its size threshold.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _summed(parts: DataFrame, rows: DataFrame, cols: list[str]) -> DataFrame:
    sums = parts.groupBy("row").agg(*[F.sum(c).alias(c) for c in cols])
    return rows.drop(*cols).join(sums, "row", "left").fillna(0.0, cols)


class IncidenceFrames:
    """vars: (var, u, v) edges; rows: vertices. The edge row is the matrix column. partial: some vertices have no row."""

    def __init__(self, partial: bool = False):
        self.how = "left" if partial else "inner"

    def forward(self, variables: DataFrame, rows: DataFrame, cols: list[str]) -> DataFrame:
        return _summed(variables.select(F.explode(F.array("u", "v")).alias("row"), *cols), rows, cols)

    def back(self, variables: DataFrame, rows: DataFrame, weight: str, name: str) -> DataFrame:
        at_u = rows.select(F.col("row").alias("u"), F.col(weight).alias("_wu"))
        at_v = rows.select(F.col("row").alias("v"), F.col(weight).alias("_wv"))
        out = variables.join(at_u, "u", self.how).join(at_v, "v", self.how)
        return out.withColumn(name, F.coalesce("_wu", F.lit(0.0)) + F.coalesce("_wv", F.lit(0.0))).drop("_wu", "_wv")


class CoverFrames:
    """The transposed incidence: vars are vertices, rows are edges (row, u, v)."""

    def forward(self, variables: DataFrame, rows: DataFrame, cols: list[str]) -> DataFrame:
        at_u = variables.select(F.col("var").alias("u"), *[F.col(c).alias(f"_u{i}") for i, c in enumerate(cols)])
        at_v = variables.select(F.col("var").alias("v"), *[F.col(c).alias(f"_v{i}") for i, c in enumerate(cols)])
        out = rows.drop(*cols).join(at_u, "u").join(at_v, "v").withColumns({c: F.col(f"_u{i}") + F.col(f"_v{i}") for i, c in enumerate(cols)})
        return out.drop(*[f"_{e}{i}" for e in "uv" for i in range(len(cols))])

    def back(self, variables: DataFrame, rows: DataFrame, weight: str, name: str) -> DataFrame:
        sums = rows.select(F.explode(F.array("u", "v")).alias("var"), F.col(weight).alias(name)).groupBy("var").agg(F.sum(name).alias(name))
        return variables.drop(name).join(sums, "var", "left").fillna(0.0, [name])


class NeighbourhoodFrames:
    """Identity plus adjacency; edges: (u, v)."""

    def __init__(self, edges: DataFrame):
        self.ways = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))

    def forward(self, variables: DataFrame, rows: DataFrame, cols: list[str]) -> DataFrame:
        own = variables.select(F.col("var").alias("row"), *cols)
        sent = self.ways.join(variables.select(F.col("var").alias("v"), *cols), "v").select(F.col("u").alias("row"), *cols)
        return _summed(own.unionByName(sent), rows, cols)

    def back(self, variables: DataFrame, rows: DataFrame, weight: str, name: str) -> DataFrame:
        as_vars = rows.select(F.col("row").alias("var"), F.col(weight).alias(name))
        return self.forward(as_vars, variables.withColumnRenamed("var", "row"), [name]).withColumnRenamed("row", "var")


class PairSumFrames:
    """vars: (var, edge, at) edge ends; rows: edges, both ends added."""

    def forward(self, variables: DataFrame, rows: DataFrame, cols: list[str]) -> DataFrame:
        return _summed(variables.select(F.col("edge").alias("row"), *cols), rows, cols)

    def back(self, variables: DataFrame, rows: DataFrame, weight: str, name: str) -> DataFrame:
        return variables.drop(name).join(rows.select(F.col("row").alias("edge"), F.col(weight).alias(name)), "edge")


class PairToVertexFrames:
    """vars: (var, edge, at) edge ends; rows: vertices, divided by a scale."""

    def __init__(self, scale: float = 1.0):
        self.scale = scale

    def forward(self, variables: DataFrame, rows: DataFrame, cols: list[str]) -> DataFrame:
        return _summed(variables.select(F.col("at").alias("row"), *[(F.col(c) / F.lit(self.scale)).alias(c) for c in cols]), rows, cols)

    def back(self, variables: DataFrame, rows: DataFrame, weight: str, name: str) -> DataFrame:
        return variables.drop(name).join(rows.select(F.col("row").alias("at"), (F.col(weight) / F.lit(self.scale)).alias(name)), "at")


class CooFrames:
    """Explicit entries (row, var, val)."""

    def __init__(self, entries: DataFrame):
        self.entries = entries.select("row", "var", F.col("val").alias("_a"))  # columns of vectors may be called val

    def forward(self, variables: DataFrame, rows: DataFrame, cols: list[str]) -> DataFrame:
        sent = self.entries.join(variables.select("var", *cols), "var").select("row", *[(F.col("_a") * F.col(c)).alias(c) for c in cols])
        return _summed(sent, rows, cols)

    def back(self, variables: DataFrame, rows: DataFrame, weight: str, name: str) -> DataFrame:
        sent = self.entries.join(rows.select("row", F.col(weight).alias(name)), "row").groupBy("var").agg(F.sum(F.col("_a") * F.col(name)).alias(name))
        return variables.drop(name).join(sent, "var", "left").fillna(0.0, [name])


class ScaledRowsFrames:
    """Rows of another operator divided by their ``bound``; rows hold that column."""

    def __init__(self, op):
        self.op = op

    def forward(self, variables: DataFrame, rows: DataFrame, cols: list[str]) -> DataFrame:
        out = self.op.forward(variables, rows, cols)
        return out.withColumns({c: F.col(c) / F.col("bound") for c in cols})

    def back(self, variables: DataFrame, rows: DataFrame, weight: str, name: str) -> DataFrame:
        return self.op.back(variables, rows.withColumn("_scaled", F.col(weight) / F.col("bound")), "_scaled", name)


def incidence_entries(edges: DataFrame) -> DataFrame:
    """The explicit incidence matrix of edges (eid, u, v), for comparison with the implicit one."""
    return edges.select(F.explode(F.array("u", "v")).alias("row"), F.col("eid").alias("var"), F.lit(1.0).alias("val"))


def tiles(entries: DataFrame, side: int) -> DataFrame:
    """(brow, bcol, cells): blocks of the matrix, each a list of (column, row, value) ordered by column."""
    cell = F.struct((F.col("var") % side).cast("int").alias("c"), (F.col("row") % side).cast("int").alias("r"), F.col("val").alias("x"))
    return entries.groupBy(F.floor(F.col("row") / side).alias("brow"), F.floor(F.col("var") / side).alias("bcol")).agg(F.sort_array(F.collect_list(cell)).alias("cells"))


def tiled_forward(blocks: DataFrame, vector: DataFrame, side: int, col: str) -> DataFrame:
    """(row, col): blocks times vector (var, col); only vector blocks and partial sums move."""
    dense = vector.groupBy(F.floor(F.col("var") / side).alias("bcol")).agg(F.map_from_entries(F.collect_list(F.struct((F.col("var") % side).cast("int"), F.col(col)))).alias("_x"))
    parts = blocks.join(dense, "bcol").select("brow", F.explode(F.transform("cells", lambda e: F.struct(e["r"].alias("r"), (e["x"] * F.coalesce(F.try_element_at("_x", e["c"]), F.lit(0.0))).alias("p")))).alias("e"))
    return parts.groupBy((F.col("brow") * side + F.col("e.r")).alias("row")).agg(F.sum("e.p").alias(col))
