"""Words and tallies of the quality rules against plain Python, and how often a word is looked up."""

import contextlib
import io
import re
from collections import Counter

from pyspark.sql import functions as F

from poslp.llm.common import words
from poslp.llm.quality_rules import COMMON, split_words, with_tally

TEXTS = [None, "", " ", "\n\t\x0b\x0c\r ", "a", "  a  b ", "the cat\x1cthe the dog the\n\nof of", "x\ty\x0bz\r\nend ", "é ö 漢字 漢字 é", "\x00 a\x00b", "the " * 300]


def test_split_words_are_the_matches(spark):
    rows = spark.createDataFrame([(t,) for t in TEXTS], "text string").select("text", split_words(F.col("text")).alias("a"), words(F.col("text")).alias("b")).collect()
    assert len(rows) == len(TEXTS)
    for r in rows:
        assert r["a"] == r["b"] == re.findall("[^\x20\x09-\x0d]+", r["text"] or ""), r["text"]


def _tallies(spark):
    common = [["the", "of", "é", "漢字"], ["a"], None]
    rows = [(i, t, c) for i, (t, c) in enumerate((t, c) for t in TEXTS for c in common)]
    docs = spark.createDataFrame(rows, "k int, text string, _common array<string>").withColumn("_words", split_words(F.col("text")))
    return {k: (t, c) for k, t, c in rows}, with_tally(docs).select("k", "_tally")


def test_tally_counts_common_words_then_all_others(spark):
    rows, tally = _tallies(spark)
    for r in tally.collect():
        text, common = rows[r["k"]]
        n = Counter(re.findall("[^\x20\x09-\x0d]+", text or ""))
        of = [n[w] for w in common or []]
        assert r["_tally"] == [*of, *[0] * (COMMON - len(of)), sum(n.values()) - sum(of)], (text, common)


def test_a_word_is_looked_up_once(spark):
    _, tally = _tallies(spark)
    said = io.StringIO()
    with contextlib.redirect_stdout(said):
        tally.explain("extended")
    plan = said.getvalue().split("== Optimized Logical Plan ==")[1].split("== Physical Plan ==")[0]
    assert plan.count("array_position(") == 1
