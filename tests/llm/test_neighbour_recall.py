"""Recall of the neighbour graph where its rounds run, with an outlier and a group of nearly equal vectors."""

import numpy as np
from pyspark.sql import functions as F

from poslp.llm import nn_descent
from poslp.llm.nn_descent import NeighbourGraph


def test_recall_with_an_outlier_and_a_jittered_group(spark, monkeypatch):
    monkeypatch.setattr(nn_descent, "BLOCK", 300)
    rng = np.random.default_rng(11)
    x = rng.normal(size=(1500, 12))
    x /= np.linalg.norm(x, axis=1)[:, None]
    x[:500] = x[0] + rng.normal(size=(500, 12)) * 1e-4
    x[-1] = 1000
    x = x.astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    out = NeighbourGraph(df, "vec_id", "embedding").search(df.where(F.col("vec_id") % 25 == 0), "vec_id", "embedding").toPandas()
    y, hit = x.astype(float), {True: [], False: []}
    for i in range(0, 1500, 25):
        d = ((y - y[i]) ** 2).sum(1)
        d[i] = np.inf
        hit[i < 500].append(len(set(out[out.query_id == i].vec_id) & set(np.argsort(d)[:10].tolist())) / 10)
    assert np.mean(hit[True]) >= 0.9 and np.mean(hit[False]) >= 0.9
    print("recall", np.mean(hit[True]), np.mean(hit[False]))
