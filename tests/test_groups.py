from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from poslp.plans import shared
from poslp.registry import oracle_sql, queries
from poslp.sources import groups
from poslp.sources.graphs import numbered

SQL = oracle_sql()


@pytest.mark.parametrize("users, spread", [(7, 1), (5000, 1), (5000, 10**12)])
def test_pairs_and_degrees_equal_all_pairs_of_each_key(spark, users, spread):
    rng = np.random.default_rng(users)
    rows = [(f"k{int(k)}", int(i) * spread - 3) for k, i in zip(rng.integers(0, users // 3, 3 * users), rng.integers(0, users, 3 * users))]
    rows += [(None, 1), (None, 2), ("k0", None), ("alone", -50)]
    keys = {}
    for k, i in rows:
        if k is not None and i is not None:
            keys.setdefault(k, set()).add(i)
    want = sorted({p for s in keys.values() for p in combinations(sorted(s), 2)})
    df = spark.createDataFrame(rows, "k string, i long")
    together = groups.Together(df, F.col("k"), F.col("i"))
    got = together.numbered().collect()
    assert sorted((r["eid"], r["u"], r["v"]) for r in got) == [(n, *p) for n, p in enumerate(want)]
    assert sorted(map(tuple, together.pairs().collect())) == want
    ends = np.array(want).ravel()
    vid, n = np.unique(ends, return_counts=True)
    assert sorted(map(tuple, together.degrees().collect())) == list(zip(vid.tolist(), n.tolist()))
    none = groups.Together(df.limit(0), F.col("k"), F.col("i"))
    assert none.numbered().count() == none.pairs().count() == none.degrees().count() == 0


def test_blocks_beyond_the_first(spark):
    """Three blocks: a hot key over all items, and the bits of each item's own block and of later ones."""
    n = 2 * groups.BLOCK + 70
    hot = [5, groups.RUN, groups.BLOCK - 1, groups.BLOCK, 2 * groups.BLOCK + 1, n - 1]
    df = spark.range(n).select(F.concat(F.lit("own"), F.col("id")).alias("k"), F.col("id").alias("i")).union(spark.createDataFrame([("hot", i) for i in hot], "k string, i long"))
    together = groups.Together(df, F.col("k"), F.col("i"))
    assert [tuple(r) for r in together.numbered().orderBy("eid").collect()] == [(e, *p) for e, p in enumerate(combinations(hot, 2))]
    assert {r["vid"]: r["degree"] for r in together.degrees().collect()} == dict.fromkeys(hot, len(hot) - 1)


def test_no_pair_is_joined_or_shuffled(spark, data):
    plan = numbered(spark, data, "user_cooccur")._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and plan.count("Exchange") == 1
    assert queries()["edges_user_cooccur"](spark, data).count() > 0


def test_the_profile_holds_one_graph_on_disk_at_a_time(spark, data, same):
    """Only one-row tables are left to read, and the session's setting is as it was."""
    profile = queries()["graph_profile"](spark, data)
    plan = profile._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Join" not in plan
    assert spark.conf.get(shared.CLEANUP, None) in (None, "true")
    same(queries()["graph_profile"], SQL["graph_profile"])
