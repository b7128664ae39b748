"""Exact k nearest neighbours by cosine for small vector tables, block against block."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def block_knn(rows: DataFrame, id_col: str, vector_col: str, k: int, side: int = 4096) -> DataFrame:
    """(a, b): each row and its k nearest others. Blocks of about ``side`` rows meet pairwise, as a full comparison
    must; each pair of blocks returns k rows a member."""
    n = rows.count()
    blocks = max(1, -(-n // side))
    rows = rows.select(F.col(id_col).alias("id"), F.col(vector_col).alias("vec"), F.pmod(F.xxhash64(id_col), F.lit(blocks)).cast("int").alias("blk"))
    # numbers of one type on both sides, or equal pairs of blocks hash apart and never meet
    numbers = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left = rows.select("id", "vec", F.col("blk").alias("i"), numbers.alias("j"))
    right = rows.select("id", "vec", F.col("blk").alias("j"), numbers.alias("i"))

    def nearest(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if not len(a) or not len(b):
            return pd.DataFrame({"a": [], "b": [], "s": []})
        x, y = (np.stack(t.vec.to_numpy()).astype(float) for t in (a, b))
        s = (x / np.linalg.norm(x, axis=1)[:, None]) @ (y / np.linalg.norm(y, axis=1)[:, None]).T
        s[a.id.to_numpy()[:, None] == b.id.to_numpy()[None, :]] = -2
        m = min(k, len(b))
        at = np.argpartition(-s, m - 1, axis=1)[:, :m]
        return pd.DataFrame({"a": np.repeat(a.id.to_numpy(), m), "b": b.id.to_numpy()[at].ravel(), "s": np.take_along_axis(s, at, 1).ravel()})

    pairs = left.groupBy("i", "j").cogroup(right.groupBy("i", "j")).applyInPandas(nearest, "a long, b long, s double")
    best = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("s"), "b"))
    return pairs.where(F.col("s") > -2).withColumn("r", best).where(F.col("r") <= k).select("a", "b")
