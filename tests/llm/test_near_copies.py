"""The near-dedup stage of the pipeline against comparing all pairs."""

import re

import numpy as np
import pytest

import corpus_pipeline
from poslp.llm import near_copies
from poslp.llm.near_copies import near_components


def grams(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", text.lower())
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or {tuple(w)}


def components(texts):
    sets, label = [grams(t) for t in texts], list(range(len(texts)))
    for i in range(len(sets)):
        for j in range(i):
            if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]) and label[i] != label[j]:
                a, b = sorted((label[i], label[j]))
                label = [a if x == b else x for x in label]
    return label


def planted(rng):
    texts = []
    for group in range(12):
        base = [f"w{x}" for x in rng.integers(0, 3000, int(rng.integers(20, 200)))]
        texts.append(" ".join(base))
        for _ in range(30 if group == 0 else 6):
            copy = list(base)
            for k in rng.integers(0, len(copy), int(rng.integers(1, max(2, len(copy) // 30)))):
                copy[k] = f"new{rng.integers(0, 10**6)}"
            texts.append(" ".join(copy))
    passage = " ".join(f"p{x}" for x in range(60))
    texts += [passage + " " + " ".join(f"q{x}" for x in rng.integers(0, 10**6, 60)) for _ in range(20)]
    return texts + ["a b c", "A b C", "a b", "x y z u v w"] + [f"{texts[5].upper()} tail"]


@pytest.mark.parametrize("sample, small", [(64, 8), (1, 2)])
def test_near_copies_equal_brute_force(spark, monkeypatch, sample, small):
    monkeypatch.setattr(near_copies, "SAMPLE", sample)
    monkeypatch.setattr(near_copies, "SMALL", small)
    texts = planted(np.random.default_rng(5))
    want = components(texts)
    assert len(set(want)) < len(texts) - 30
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in near_components(docs).collect()}
    assert [got[i] for i in range(len(texts))] == want
    kept = corpus_pipeline.near_dedup(spark, docs, "").collect()
    assert sorted(r["doc_id"] for r in kept) == sorted(set(want))


def test_odd_rows(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (None, "a b"), (None, "a b"), (3, "a b"), (3, "a b"), (3, "c d")], "doc_id long, text string")
    kept = corpus_pipeline.near_dedup(spark, docs, "").collect()
    assert sorted(str(r["doc_id"]) for r in kept) == ["1", "3", "None", "None"]
    assert near_components(docs.limit(0)).count() == 0


def test_joined_nodes_are_not_compared_again(spark, monkeypatch):
    """A pair carries whole sets, so copies of one text cost about as many pairs as there are copies."""
    looked, run = [], near_copies.confirmed
    monkeypatch.setattr(near_copies, "confirmed", lambda pairs, *a: looked.append(pairs.count()) or run(pairs, *a))
    base = [f"w{x}" for x in range(400)]
    texts = [" ".join([*base[:k], f"new{k}", *base[k + 1 :]]) for k in range(0, 400, 50)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {r["component_id"] for r in near_components(docs).collect()} == {0}
    assert sum(looked) <= len(texts)
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == "true"


def test_long_texts_that_share_a_passage_are_told_apart_by_their_bitmaps(spark, monkeypatch):
    """A bitmap of 1,024 bits is full for texts of 3,000 words and bounds nothing."""
    looked, run = [], near_copies.confirmed
    monkeypatch.setattr(near_copies, "confirmed", lambda pairs, *a: looked.append(pairs.count()) or run(pairs, *a))
    passage = " ".join(f"p{x}" for x in range(300))
    texts = [f"{passage} " + " ".join(f"t{k}w{x}" for x in range(2700)) for k in range(12)]
    near = texts[0].replace("t0w5 ", "other ")
    docs = spark.createDataFrame(list(enumerate([*texts, near])), "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in near_components(docs).collect()}
    assert got == {k: k for k in range(12)} | {12: 0}
    assert sum(looked) == 1


def test_bitmaps_of_two_widths_never_rule_out_a_similar_pair():
    rng = np.random.default_rng(3)
    for n in (3, 500, 512, 513, 1000, 1024, 1025, 16384, 16500, 40000):
        m = -(-4 * n // 5)
        x = np.unique(rng.integers(-(2**63), 2**63 - 1, n))
        y = x[rng.permutation(len(x))[:m]]
        width = near_copies._widths(np.array([len(x), len(y)]))
        maps = []
        for values, w in zip((x, y), width):
            seen = np.zeros(w, dtype=bool)
            seen[values & (w - 1)] = True
            maps.append(np.packbits(seen).tobytes())
        size = np.array([len(x), len(y)])
        assert near_copies._Bitmaps(maps).within(np.array([0]), np.array([1]), size).all(), (n, width)
