"""Words that hold several candidates."""

import hashlib

import pytest
from pyspark.sql import functions as F

from poslp.llm import secret_scan as scan
from poslp.llm.secret_scan import candidates, training_rows, verified_labels, with_features


def test_every_run_of_a_word_is_a_candidate(spark):
    key = hashlib.sha256(b"k").hexdigest()[:40]
    json = f'{{"AWS_SECRET_ACCESS_KEY":"{key}","é":"{key[::-1]}"}}'
    url = f"https://h.example/{key}?{'a' * 20},{'b' * 16},{'c' * 15}"
    docs = spark.createDataFrame([(1, "s", f"set {json} now"), (2, "s", f"{url} end")], "doc_id long, source string, text string")
    rows = verified_labels(with_features(candidates(docs), [])).collect()
    got = {(r["doc_id"], r["place"], r["offset"]): r for r in rows}
    want = {(1, 1, 2): "AWS_SECRET_ACCESS_KEY", (1, 1, json.index(key)): key, (1, 1, json.index(key[::-1])): key[::-1], (2, 0, url.index("example/")): "example/" + key}
    want |= {(2, 0, url.index("aaaa")): "a" * 20, (2, 0, url.index("bbbb")): "b" * 16}
    assert {at: r["candidate"] for at, r in got.items()} == want and len(rows) == 6
    secret = got[1, 1, json.index(key)]
    assert secret["named"] == 1 and secret["assigned"] == 1 and secret["quoted"] == 1 and secret["_label"] == 1.0
    assert not got[1, 1, json.index(key[::-1])]["named"]


def test_an_assigned_value_stands_apart_from_its_name(spark):
    key = "ghp_" + hashlib.sha256(b"k").hexdigest()[:36]
    docs = spark.createDataFrame([(1, "s", f"MY_SECRET_ACCESS_KEY={key}"), (2, "s", f"token={'Ab1+' * 10}=="), (3, "s", f"x={'aB3/' * 10}")], "doc_id long, source string, text string")
    rows = verified_labels(with_features(candidates(docs), [])).orderBy("doc_id", "offset").collect()
    assert [(r["doc_id"], r["candidate"], r["_label"]) for r in rows] == [(1, "MY_SECRET_ACCESS_KEY", None), (1, key, 1.0), (2, "Ab1+" * 10 + "==", 1.0), (3, "aB3/" * 10, None)]


def test_transitions_are_shares_of_neighbouring_characters(spark):
    docs = spark.createDataFrame([(1, "s", "aaaaBBBB1111----")], "doc_id long, source string, text string")
    r = with_features(candidates(docs), []).first()
    got = {p: round(15 * r[f"pair_{p}"]) for p in scan.PAIRS if r[f"pair_{p}"]}
    assert got == {"ll": 3, "lu": 1, "uu": 3, "ud": 1, "dd": 3, "d-": 1, "--": 3} and r["changes"] == 3


@pytest.mark.parametrize("hot", [0.0, 1.0])
def test_a_hot_group_leaves_room_for_both_labels(spark, monkeypatch, hot):
    """Equal findings of one label beyond the bound, whatever their hash, next to few of the other."""
    monkeypatch.setattr(scan, "TRAIN_ROWS", 20)
    rows = spark.range(120).withColumnsRenamed({"id": "doc_id"}).withColumn("_label", F.when(F.col("doc_id") < 90, hot).otherwise(1 - hot))
    rows = rows.withColumns({c: F.when(F.col("doc_id") < 90, 1.0).otherwise(F.col("doc_id").cast("double")) for c in scan.FEATURES})
    got = {r["_label"]: (r["n"], r["w"]) for r in training_rows(rows).groupBy("_label").agg(F.count("*").alias("n"), F.sum("_weight").alias("w")).collect()}
    assert got == {hot: (10, 90.0), 1 - hot: (10, 30.0)}
