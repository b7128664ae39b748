"""Nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from poslp.llm.chat_format import chat_format
from poslp.llm.line_dedup import line_dedup
from poslp.llm.mixing import mix
from poslp.llm.nn_descent import NeighbourGraph
from poslp.llm.packing import pack, pieces
from poslp.llm.common import materialise
from poslp.llm.quality_rules import judge, measure
from poslp.llm.secret_scan import secret_scan
from poslp.llm.simhash import fingerprints, simhash_components
from poslp.llm.suffix_dedup import suffix_dedup
from poslp.llm.token_blocks import token_blocks

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _id string, anchor long, length string"
LONG = "word " * 20000


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "one two", "en", "a", 7), (3, "one two", "en", "a", 7), (None, "x" * 300, "en", "b", 300), (4, LONG, "de", "b", len(LONG)), (5, " \t\n\r ", "", "", 5), (6, "é\U0001f600 \u0000 z", "fr", "c", 6)]
    return spark.createDataFrame([(*r, "i", 7, "l") for r in rows], SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def test_line_dedup(odd, none):
    out = line_dedup(odd)
    assert out.count() == odd.count() and line_dedup(none).count() == 0
    assert {r["doc_id"]: (r["_n_lines"], r["text"]) for r in out.collect()}[2] == (1, "")


def test_line_dedup_keeps_the_last_holder(spark):
    line = "This line is long enough to be counted as shared text."
    docs = spark.createDataFrame([(i, f"own {i}\n  {line.upper() if i % 2 else line}\t\nend") for i in range(6)], "doc_id long, text string")
    got = {r["doc_id"]: r for r in line_dedup(docs).collect()}
    assert all(got[i]["_n_dropped"] == 1 and got[i]["text"] == f"own {i}\nend" for i in range(5)) and got[5]["_n_dropped"] == 0


def test_line_dedup_counts_documents_not_rows(spark):
    line = "A line of more than forty characters that some documents share."
    docs = spark.createDataFrame([(1, line)] * 3 + [(2, line), (3, line), (None, line)], "doc_id long, text string")
    assert all(r["_n_dropped"] == 0 for r in line_dedup(docs).collect())
    more = docs.unionByName(spark.createDataFrame([(4, line), (5, line)], docs.schema))
    assert sorted((str(r["doc_id"]), r["_n_dropped"]) for r in line_dedup(more).collect()) == [("1", 1)] * 3 + [("2", 1), ("3", 1), ("4", 1), ("5", 0), ("None", 0)]


def test_quality_has_a_reference_for_every_long_language(spark):
    """More languages than any fixed cap; in each, one document of another script beside many of its own."""
    from poslp.llm import quality_rules as rules

    rows = []
    for k in range(300):
        own = " ".join(chr(0x4E00 + 40 * k + i % 37) + chr(0x4E00 + 40 * k + i % 31) for i in range(700))
        rows += [(10 * k + j, own, f"l{k}") for j in range(3)]
    rows += [(9001, "### $$$ %%% " * 100, "l7"), (9002, "lone words here " * 100, "alone")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    out = {r["doc_id"]: r for r in rules.measure(docs).collect()}
    assert all(out[d]["_class_js"] < 0.1 and out[d]["_word_js"] < 0.1 for d in out if d < 9000 and d // 10 != 7)
    assert out[9001]["_class_js"] > rules.MAX_CLASS_DISTANCE and out[71]["_class_js"] < rules.MAX_CLASS_DISTANCE
    assert out[9002]["_class_js"] > 0.3  # 300 words are no reference of their own


def test_quality(odd, none):
    out = judge(measure(odd, odd.columns)).select("_row.*", "n_words", "base_failed", "kept").collect()
    assert len(out) == odd.count() and judge(measure(none)).count() == 0
    by = {r["doc_id"]: r for r in out}
    assert by[1]["n_words"] == 0 and by[1]["base_failed"] and by[4]["base_failed"] and by[4]["n_words"] == 20000


def test_simhash(odd, none, spark):
    prints = materialise(fingerprints(odd), "t")
    out = simhash_components(prints).collect()
    by = {r["doc_id"]: r for r in out}
    assert len(out) == odd.count() and by[1]["fp"] == by[2]["fp"] == by[5]["fp"] == 0 and by[5]["component_id"] == 1
    assert simhash_components(materialise(fingerprints(none), "t")).count() == 0


def test_packing(odd, none):
    cut = materialise(pieces(odd), "t")
    rows = pack(cut).toPandas().sort_values(["sequence_id", "offset"])
    assert len(rows) == cut.count() and (rows.groupby("sequence_id").length.sum() <= 1024).all()
    assert (rows.groupby("sequence_id").length.cumsum() - rows.length == rows.offset).all()
    assert pack(materialise(pieces(none), "t")).count() == 0


def test_blocks(odd, none):
    rows = token_blocks(odd, window=64, digest=True).collect()
    assert sum(len(r["doc_ids"]) for r in rows) >= odd.count() and all(len(r["ids"]) == 128 for r in rows)
    assert token_blocks(none).count() == 0


def test_mixing(odd, none):
    out = mix(odd)
    assert out.select(*odd.columns).distinct().count() == odd.distinct().count() and mix(none).count() == 0


def test_secrets(odd, none, spark):
    assert [(r["doc_id"], r["candidate"], r["score"]) for r in secret_scan(odd).collect()] == [(None, "x" * 300, 0.0)]
    assert secret_scan(none).count() == 0
    twice = spark.createDataFrame([(1, "s", "password=deadbeefdeadbeef0123 " * 2)] * 2 + [(2, "s", "number 1234567890123456789")], "doc_id long, source string, text string")
    rows = secret_scan(twice).collect()
    assert len(rows) == 5 and {(r["candidate"], r["place"]) for r in rows if r["doc_id"] == 1} == {("deadbeefdeadbeef0123", 0), ("deadbeefdeadbeef0123", 1)}
    long = spark.createDataFrame([(1, "s", "word " * 200_000 + "token=" + "a1" * 16)], twice.schema)
    assert [r["place"] for r in secret_scan(long).collect()] == [200_000]


def test_suffix(odd, none):
    got = suffix_dedup(odd)
    by = {r["doc_id"]: r for r in got.collect()}
    assert got.count() == odd.count() and suffix_dedup(none).count() == 0
    assert by[4]["n_removed"] == len(LONG) and by[None]["n_removed"] == 300 and by[1]["kept_sha256"] == hashlib.sha256(b"").hexdigest()


def test_suffix_of_equal_rows(spark):
    text = "".join(chr(97 + (i * i * 7 + i // 3) % 26) for i in range(250))
    docs = spark.createDataFrame([(1, text), (1, text), (2, text[:199])], "doc_id long, text string")
    assert sorted((r["doc_id"], r["n_removed"]) for r in suffix_dedup(docs).collect()) == [(1, 250), (1, 250), (2, 0)]


def test_chat(spark):
    turns = [("a", 0, "user", "hi"), ("a", 1, "assistant", "yo"), ("b", 0, "user", "hi"), ("b", 1, "assistant", "yo"), ("b", 2, "user", "go <|im_end|>"), ("c", 0, "user", "hi"), ("d", 0, None, None), ("e", 0, "unknown", ""), (None, 0, "user", "alone"), ("b2", 0, "user", "hi"), ("b2", 1, "assistant", "yo"), ("b2", 2, "user", "go <|im_end|>")]
    df = spark.createDataFrame(turns, "conv_id string, turn long, role string, text string").withColumn("_key", F.lit(1))
    out = {r["conv_id"]: r for r in chat_format(df).collect()}
    assert set(out) == {"b", "d", "e", None} and out["b"]["n_turns"] == 3 and out["b"]["rendered"].count("<|im_end|>") == 3
    assert chat_format(df.limit(0)).count() == 0


def test_neighbours(spark):
    rows = [(i, [float(i % 3), float(i // 3), 1.0]) for i in range(9)] + [(20, None), (21, [0.0, 0.0, 0.0]), (22, [1.0, None, 0.0]), (23, [1.0, float("nan"), 0.0]), (24, [1.0]), (30, [0.0, 0.0, 1.0]), (30, [0.0, 0.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("code", F.lit(1))
    out = NeighbourGraph(df, "vec_id", "embedding").search(df.where("vec_id in (0, 20, 30)"), "vec_id", "embedding").toPandas()
    assert set(out.query_id) == {0, 30} and out[(out.query_id == 0) & (out["rank"] == 1)].vec_id.item() == 30
    assert len(out[out.query_id == 0]) == 9
    assert NeighbourGraph(df.limit(0), "vec_id", "embedding").search(df.limit(0), "vec_id", "embedding").count() == 0
    new = spark.createDataFrame([(99, [0.1, 0.1, 1.0])], "vec_id long, embedding array<float>")
    far = NeighbourGraph(df, "vec_id", "embedding").search(new, "vec_id", "embedding", k=2).toPandas()
    assert list(far.vec_id) == [0, 30] and np.allclose(far.score, np.sqrt(0.02), atol=1e-7)
