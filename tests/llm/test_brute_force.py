"""Every query on a whole small table against a plain computation of its contract."""

import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash

import corpus_pipeline
from poslp.llm import registry, suffix_dedup
from poslp.llm.common import materialise
from poslp.llm.fill_plan import best_fit_decreasing
from poslp.llm.induced_sort import sort_suffixes
from poslp.llm.packing import nnls_plan
from poslp.llm.secret_scan import CANDIDATE
from poslp.llm.tokens import encoder

Q = registry.queries()
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
WORDS = lambda t: re.findall(r"[^\x20\x09-\x0D]+", t or "")


@pytest.fixture(scope="module")
def docs(spark, data):
    return spark.read.parquet(f"{data}/documents.parquet").toPandas()


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_sql(name, same):
    same(Q[name], registry.oracle_sql()[name])


def test_neighbours_recall(spark, data):
    out = Q["op1_nn_descent"](spark, data).toPandas()
    rows = spark.read.parquet(f"{data}/embeddings.parquet").toPandas()
    x, ids, hit = np.stack(rows.embedding.to_numpy()).astype(float), rows.vec_id.to_numpy(), 0
    queries = np.flatnonzero(ids % 100 == 0)
    for i in queries:
        d = np.sqrt(((x - x[i]) ** 2).sum(1))
        d[i] = np.inf
        got = out[out.query_id == ids[i]].sort_values("rank")
        hit += len(set(got.vec_id) & set(ids[np.lexsort((ids, d))[:10]]))
        assert np.allclose(got.score, d[[int(np.flatnonzero(ids == v)[0]) for v in got.vec_id]], rtol=1e-12)
    assert hit >= 0.9 * 10 * len(queries)


def test_secrets_held_out(spark):
    """Trained on labelled findings of one half, the forest sorts those of the other."""
    from pyspark.sql import functions as F

    from poslp.llm.secret_scan import candidates, dictionary, secret_scan, with_features

    rows = []
    for i in range(160):
        h = hashlib.sha256(str(i).encode()).hexdigest()
        secret = [f'the token = "{h[:40]}" was', f"set api_key: {h[:32]} here", f"password={h[:20].upper()}x1 and"][i % 3]
        decoy = [f"pay {int(h[:14], 16):016d} now", "somethingwordwordsomethingword is", f"see commit {'word' * 5} there"][i % 3]
        rows.append((i, "src", f"some word some word something {secret if i % 2 else decoy} something word some word"))
    docs = spark.createDataFrame(rows, "doc_id long, source string, text string")
    train, rest = docs.where("doc_id < 80"), docs.where("doc_id >= 80")
    labelled = with_features(candidates(train), dictionary(train)).withColumn("_label", (F.col("doc_id") % 2).cast("double"))
    out = secret_scan(rest, labelled).toPandas()
    assert ((out.score >= 0.5) == (out.doc_id % 2 == 1)).mean() >= 0.95 and set(out.doc_id) == set(range(80, 160))


def test_secret_query(spark, data, docs):
    out = Q["op2_secret_scan"](spark, data).toPandas()
    want = Counter((d, hashlib.sha256(x.encode()).hexdigest()) for d, t in zip(docs.doc_id, docs.text) for w in WORDS(t) for x in re.findall(CANDIDATE, w))
    assert Counter(zip(out.doc_id, out.candidate_sha256)) == want


def test_packing(spark, data, docs):
    out = Q["op3_packing"](spark, data).toPandas()
    encode = encoder()
    for r in docs.itertuples():
        ids = np.append(encode(r.text or ""), 0).astype("<u4")
        mine = out[out.doc_id == r.doc_id].sort_values("start")
        assert mine.length.sum() == len(ids) == mine.doc_tokens.iloc[0]
        assert all(zlib.crc32(ids[s : s + n].tobytes()) == c for s, n, c in zip(mine.start, mine.length, mine.ids_crc32))
    filled = out.groupby("sequence_id").length.sum()
    assert filled.max() <= 1024 and filled.sum() / 1024 / len(filled) > 0.95


def test_ids_are_those_of_the_tokenizers_file(docs):
    import public_tokenizers
    from tokenizers import Tokenizer

    t, encode = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json")), encoder()
    odd = ["", " ", "  a", "a\n\n b", "é\U0001f600‍", "<|endoftext|>", "a <|endoftext|> b", "<|endoftext|><|endoftext|>  x <|endoftext", "a  <|endoftext|>  <|endoftext|>\n", "x" * 3000, "1234567 89", "don't I'LL", "你好世界", "tab\tand space"]
    for text in [*docs.text.dropna(), *odd]:
        assert encode(text).tolist() == t.encode(text, add_special_tokens=False).ids


def test_plans_use_each_piece_once():
    rng = np.random.default_rng(0)
    for _ in range(5):
        counts = np.zeros(257, dtype=np.int64)
        np.add.at(counts, rng.integers(1, 257, 600), 1)
        for plan in (nnls_plan(counts, 256), best_fit_decreasing(counts, 256)):
            used = np.zeros(257, dtype=np.int64)
            for combo, times in plan:
                assert sum(combo) <= 256 and times > 0
                np.add.at(used, list(combo), times)
            assert (used == counts).all()


def test_best_fit_on_the_histogram_equals_one_by_one():
    rng = np.random.default_rng(1)
    for _ in range(20):
        lengths = rng.integers(1, 33, 80)
        room: list[int] = []
        for x in sorted(lengths.tolist(), reverse=True):
            best = min((r for r in room if r >= x), default=None)
            if best is None:
                room.append(32 - x)
            else:
                room[room.index(best)] -= x
        plan = best_fit_decreasing(np.bincount(lengths, minlength=33), 32)
        assert sum(n for _, n in plan) == len(room)
        assert sorted(room) == sorted(r for combo, n in plan for r in [32 - sum(combo)] * n)


def test_mixing_weights(spark, data, docs):
    out = Q["op5_mixing"](spark, data).toPandas()
    assert set(out.doc_id) == set(docs.doc_id)
    have = docs.assign(n=[len(WORDS(t)) for t in docs.text]).groupby("source").n.sum()
    got = out.groupby("source").n_tokens.sum()
    share, repeats = have / have.sum(), got / have
    assert repeats.min() > 0.99 and repeats.max() <= 2.001
    power = np.polyfit(np.log(share), np.log(repeats * share), 1)[0]
    assert 0 <= power < 1 and np.corrcoef(np.log(share), np.log(repeats))[0, 1] < -0.7
    whole = out.groupby(["source", "epoch"]).doc_id.nunique()
    assert (whole[:, 0] == docs.groupby("source").doc_id.nunique()).all()


@pytest.mark.parametrize("hot", [1, 20_000])
def test_suffixes(spark, data, docs, hot, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "HOT", hot)
    out = Q["op6_suffix_dedup"](spark, data).toPandas().set_index("doc_id")
    raw = {r.doc_id: (r.text or "").encode() for r in docs.itertuples()}
    seen = Counter(hash(t[k : k + 200]) for t in raw.values() for k in range(len(t) - 199))
    for i, t in raw.items():
        gone = np.zeros(len(t), dtype=bool)
        for k in range(len(t) - 199):
            if seen[hash(t[k : k + 200])] > 1:
                gone[k : k + 200] = True
        kept = bytes(np.frombuffer(t, np.uint8)[~gone])
        r = out.loc[i]
        assert (r.n_bytes, r.n_removed, r.kept_sha256) == (len(t), int(gone.sum()), hashlib.sha256(kept).hexdigest())
        assert r.n_spans == int((np.diff(np.r_[0, gone.astype(int)]) == 1).sum())


@pytest.mark.parametrize("budget", [64, 1 << 20])
def test_induced_sort(budget):
    rng = np.random.default_rng(budget)
    for _ in range(40):
        t = rng.integers(1, rng.integers(2, 7), rng.integers(1, 300)).astype(np.uint8)
        parts = list(sort_suffixes(t, 50, budget))[::-1]
        pos, lcp = np.concatenate([p for p, _ in parts]), np.concatenate([c for _, c in parts])
        b = t.tobytes()
        assert [b[i : i + 50] for i in pos] == [b[i : i + 50] for i in sorted(range(len(b)), key=lambda i: b[i:])]
        for k in range(1, len(pos)):
            x, y = b[pos[k - 1] :], b[pos[k] :]
            assert lcp[k] == next((m for m in range(min(len(x), len(y), 50)) if x[m] != y[m]), min(len(x), len(y), 50))


def test_quality(spark, data, docs):
    out = Q["op7_quality_rules"](spark, data).toPandas().set_index("doc_id")
    for r in docs.itertuples():
        w = WORDS(r.text)
        tri = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
        many, cover = Counter(tri), set()
        for k, g in enumerate(tri):
            if many[g] > 1:
                cover |= {k, k + 1, k + 2}
        full = [x for x in (r.text or "").split("\n") if WORDS(x)]
        want = (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", r.text or "")), len(full) - len(set(full)), len(cover))
        got = out.loc[r.doc_id]
        assert tuple(got[["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]]) == want
        assert got.base_failed == (len(w) < 50 or 100 * len(cover) > 50 * len(w))
    labels = spark.read.parquet(f"{data}/labels.parquet").toPandas().set_index("doc_id").join(out)
    judged = labels[~labels.base_failed.astype(bool)]
    assert judged[judged.quality == 1].kept.mean() > 0.97 and (~judged[judged.quality == 0].kept.astype(bool)).mean() > 0.9


def test_simhash(spark, data, docs):
    out = Q["op10_simhash"](spark, data).toPandas().set_index("doc_id")
    prints = []
    for t in docs.text:
        w = WORDS((t or "").translate(LOWER))
        grams = [" ".join(w[i : i + 4]) for i in range(len(w) - 3)] or ([" ".join(w)] if w else [])
        h = np.array([xxhash.xxh64_intdigest(g.encode(), seed=42) for g in grams], dtype=np.uint64)
        prints.append(sum(1 << b for b in range(64) if len(h) and 2 * int(((h >> np.uint64(b)) & np.uint64(1)).sum()) > len(h)))
    f, ids = np.array(prints, dtype=np.uint64), docs.doc_id.to_numpy()
    near, label = np.bitwise_count(f[:, None] ^ f[None, :]) <= 4, ids.copy()
    while (new := np.array([label[near[i]].min() for i in range(len(ids))])).tolist() != label.tolist():
        label = new
    assert all(out.loc[i].fingerprint == f"{p:016x}" and out.loc[i].component_id == c for i, p, c in zip(ids, prints, label))


def test_anchors_lose_no_link(spark):
    from poslp.llm.simhash import linked_fingerprints
    from poslp.llm.components import connected_components

    rng = np.random.default_rng(3)
    f = []
    for _ in range(60):
        x = int(rng.integers(0, 1 << 63))
        f.append(x)
        for _ in range(int(rng.integers(0, 12))):
            x ^= sum(1 << int(b) for b in rng.choice(64, int(rng.integers(1, 7)), replace=False))
            f.append(x)
    f = sorted(set(f))
    df = spark.createDataFrame([(int(np.uint64(x).astype(np.int64)),) for x in f], "fp long")
    got = {r["node"]: r["component"] for r in connected_components(materialise(linked_fingerprints(df), "t")).collect()}
    a = np.array(f, dtype=np.uint64)
    label = a.view(np.int64).copy()
    near = np.bitwise_count(a[:, None] ^ a[None, :]) <= 4
    while (new := np.array([label[near[i]].min() for i in range(len(a))])).tolist() != label.tolist():
        label = new
    assert all(got.get(int(x), int(x)) == int(c) for x, c in zip(a.view(np.int64), label))


def test_blocks_round_trip(spark, data, docs):
    out, encode, parts = Q["op9_token_blocks"](spark, data).toPandas(), encoder(), {}
    for r in out.itertuples():
        ids = np.frombuffer(r.ids, "<u2")
        assert len(ids) == 2048 and (ids[r.n_tokens :] == 0).all() and zlib.crc32(ids.astype("<u4").tobytes()) == r.ids_crc32
        for k, (d, s) in enumerate(zip(r.doc_ids, r.starts)):
            parts.setdefault(d, {})[s] = ids[r.cu_seqlens[k] : r.cu_seqlens[k + 1]]
    for r in docs.itertuples():
        assert np.concatenate([parts[r.doc_id][s] for s in sorted(parts[r.doc_id])]).tolist() == [*encode(r.text or "").tolist(), 0]


def test_pipeline(spark, data, docs):
    now, seen = spark.read.parquet(f"{data}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        before = now
        now = materialise(stage(spark, now, data), "stage")
        seen[name] = (before.count(), now.count())
        if name != "packing":
            assert now.columns == list(docs.columns)
    kept, whole = seen["quality rules"][1], Q["op7_quality_rules"](spark, data).where("kept").count()
    assert kept == whole and seen["line dedup"][0] == seen["line dedup"][1] and seen["simhash near-dedup"][1] <= seen["simhash near-dedup"][0] <= kept
    assert seen["mixing"][1] >= seen["mixing"][0]
    rows = now.toPandas()
    assert (rows.groupby("sequence_id").length.sum() <= 1024).all()
