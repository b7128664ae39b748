"""Removal of byte passages that occur more than once, by external induced suffix sorting of shards.

Every window of ``length`` bytes has an anchor: the 40-byte string in it of least hash, the leftmost on ties. Equal
windows have equal anchors, so suffixes are sharded by anchor and each shard can be sorted alone. Runs of windows with
one anchor form a segment. Counting the segments of each anchor hash (with map-side combine) leaves out what is
unique. Equal segments collapse to one with a count: a group of copies needs no sorting. Where segments of one anchor
differ, one of each kind has its bytes read and goes to a shard; there ``induced_sort`` orders the suffixes and their
common prefixes, with queues on disk beyond a memory budget, and each run of suffixes that share ``length`` bytes is a
repeated string. Segments whose text beside the anchor no other shares are left out before. An anchor with more than ``HOT`` kinds (the edge of a passage that very many texts share) is split by
the hash of the whole window instead, so no group grows with the data.

A text is known by the hash of its id and bytes; windows are judged on the input. Passages of all occurrences go,
the first included, as every one of them also starts elsewhere.

Defined results: null or empty text has no bytes; texts shorter than the length lose nothing; repeated rows are
separate texts; a null id is allowed; an empty table gives an empty table; only the id and text columns are read.
"""

from __future__ import annotations

import gc
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from poslp.llm.common import discard, materialise, table
from poslp.llm.induced_sort import sort_suffixes

LENGTH = 200
ANCHOR = 40
#: Kinds of segments to an anchor, beyond which it is split by whole windows: up to 8 MB of text for one task.
HOT = 20_000
#: Bytes that a task sorts at once at least; a group is never split, and has at most HOT segments.
SHARD = 1 << 21
_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Hashes:
    """Hashes of any substring of a byte string, from prefix sums over the 64-bit ring."""

    codes = _mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95))
    up, down = np.ones(1, np.uint64), np.ones(1, np.uint64)

    def __init__(self, raw: np.ndarray, salt: int = 0):
        n = len(raw)
        if len(Hashes.up) <= n:
            m = 1 << (n + 1).bit_length()
            with np.errstate(over="ignore"):
                Hashes.up = np.cumprod(np.r_[np.uint64(1), np.full(m, _MULTIPLIER)], dtype=np.uint64)
                Hashes.down = np.cumprod(np.r_[np.uint64(1), np.full(m, _INVERSE)], dtype=np.uint64)
        codes = self.codes if not salt else _mix(self.codes + np.uint64(salt))
        self.sums = np.r_[np.uint64(0), np.cumsum(codes[raw] * self.up[:n], dtype=np.uint64)]

    def of(self, start, end) -> np.ndarray:
        return _mix((self.sums[end] - self.sums[start]) * self.down[start])

    def rolling(self, k: int) -> np.ndarray:
        """Of each substring of k bytes, by a shorter mixing."""
        x = (self.sums[k:] - self.sums[:-k]) * self.down[: len(self.sums) - k]
        x ^= x >> np.uint64(32)
        x *= np.uint64(0x94D049BB133111EB)
        x ^= x >> np.uint64(29)
        return x


def sliding_least(x: np.ndarray, w: int) -> np.ndarray:
    """For each window of w values the place of the least by its upper 44 bits, the leftmost on ties."""
    n, most = len(x) - w + 1, 1 << 20
    out = np.empty(n, dtype=np.int64)
    for s in range(0, n, most - w):
        part = x[s : s + most - 1]
        key = (part >> np.uint64(20) << np.uint64(20)) | np.arange(len(part), dtype=np.uint64)
        wide = np.r_[key, np.full(-len(key) % w, np.iinfo(np.uint64).max, dtype=np.uint64)].reshape(-1, w)
        right = np.minimum.accumulate(wide, axis=1).ravel()
        left = np.minimum.accumulate(wide[:, ::-1], axis=1)[:, ::-1].ravel()
        m = len(part) - w + 1
        out[s : s + m] = (np.minimum(left[:m], right[w - 1 : w - 1 + m]) & np.uint64(most - 1)).astype(np.int64) + s
    return out


def segments(parts: list[bytes], length: int = LENGTH) -> tuple[np.ndarray, ...]:
    """(part, anchor hash, segment hash, start, end) of the runs of windows with one anchor; the windows of a segment
    start at start..end-length of its part. Parts are hashed together, windows across parts are left out."""
    size = np.array([len(p) for p in parts], dtype=np.int64)
    begin = np.cumsum(size) - size
    counts = np.maximum(0, size - length + 1)
    if not counts.sum():
        return tuple(np.empty(0, t) for t in (np.int64, np.uint64, np.uint64, np.int64, np.int64))
    h = Hashes(np.frombuffer(b"".join(parts), np.uint8))
    grams = h.rolling(ANCHOR)
    place = sliding_least(grams, length - ANCHOR + 1)
    owner = np.repeat(np.arange(len(parts)), counts)
    at = np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts - begin, counts)
    mine = place[at]
    first = np.flatnonzero(np.r_[True, (mine[1:] != mine[:-1]) | (owner[1:] != owner[:-1])])
    last = np.r_[first[1:], len(at)] - 1
    start, end, part = at[first], at[last] + length, owner[first]
    return part, grams[mine[first]], _mix(h.of(start, end) ^ (end - start).astype(np.uint64)), start - begin[part], end - begin[part]


def _emit(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def found(keys: list[int], parts: list[bytes]) -> pa.RecordBatch:
            part, anchor, kind, start, end = segments(parts, length)
            columns = (anchor.view(np.int64), kind.view(np.int64), np.array(keys, dtype=np.int64)[part], start, end)
            return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["anchor", "kind", "key", "start", "end"])

        for batch in batches:
            keys, parts, n = [], [], 0
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                keys.append(key)
                parts.append(text.as_py().encode())
                n += len(parts[-1])
                if n >= 1 << 19:
                    yield found(keys, parts)
                    keys, parts, n = [], [], 0
            if keys:
                yield found(keys, parts)

    return run


def _pieces(length: int, windows: bool):
    """Reads the bytes of the wanted segments of each text; windows: hashes of each window in place of the bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for key, text, wanted in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2)):
                raw = text.as_py().encode()
                want = wanted.as_py()
                if not windows:
                    yield pa.RecordBatch.from_arrays([pa.array([w["anchor"] for w in want], pa.int64()), pa.array([key] * len(want), pa.int64()), pa.array([w["start"] for w in want], pa.int64()), pa.array([raw[w["start"] : w["end"]] for w in want], pa.binary())], names=["anchor", "key", "start", "raw"])
                    continue
                whole = np.frombuffer(raw, np.uint8)
                at = np.concatenate([np.arange(w["start"], w["end"] - length + 1) for w in want])
                many = np.concatenate([np.full(w["end"] - length + 1 - w["start"], w["n"]) for w in want])
                a, b = Hashes(whole).of(at, at + length), Hashes(whole, 1).of(at, at + length)
                yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64)), pa.array(np.full(len(at), key, np.int64)), pa.array(at), pa.array(many)], names=["a", "b", "key", "start", "n"])

    return run


def repeated_windows(parts: list[bytes], length: int, budget: int = 1 << 28) -> list[np.ndarray]:
    """For each part the starts of its windows that also start elsewhere among the parts (same part included)."""
    if not parts:
        return []
    joined = np.frombuffer(b"\xff".join(parts) + b"\xff", np.uint8)
    text = np.where(joined == 255, np.uint8(1), joined + np.uint8(2)).astype(np.uint8)  # UTF-8 has no byte above 0xF4
    size = np.array([len(p) for p in parts])
    begin = np.cumsum(np.r_[0, size[:-1] + 1])
    hits = []
    for pos, lcp in sort_suffixes(text, length, budget):
        long = lcp >= length
        hits.append(pos[long | np.r_[long[1:], False]])
    found = np.sort(np.concatenate(hits)) if hits else np.empty(0, np.int64)
    owner = np.searchsorted(begin, found, side="right") - 1
    fits = found - begin[owner] + length <= size[owner]
    found, owner = found[fits], owner[fits]
    return np.split(found - begin[owner], np.searchsorted(owner, np.arange(1, len(parts))))


def may_repeat(anchors: np.ndarray, parts: list[bytes], length: int) -> np.ndarray:
    """Which segments can share a window with another one of their anchor. A window holds the anchor and the half of the
    rest on its left or on its right, so that half must agree too."""
    half = (length - ANCHOR) // 2
    size = np.array([len(p) for p in parts])
    begin = np.cumsum(size) - size
    h = Hashes(np.frombuffer(b"".join(parts), np.uint8))
    owner = np.repeat(np.arange(len(parts)), size)
    grams = h.rolling(ANCHOR)
    at = np.flatnonzero(grams == anchors.view(np.uint64)[owner[: len(grams)]])
    # the anchor of all windows of a segment is the first in its last window
    at = at[(at - begin[owner[at]] >= size[owner[at]] - length) & (at + ANCHOR <= begin[owner[at]] + size[owner[at]])]
    who, first = np.unique(owner[at], return_index=True)
    place = np.full(len(parts), -1)
    place[who] = at[first]
    out = place < 0  # not found: left to the sorting
    for start, end in ((place - half, place), (place + ANCHOR, place + ANCHOR + half)):
        fits = np.flatnonzero((place >= 0) & (start >= begin) & (end <= begin + size))
        key = _mix(h.of(start[fits], end[fits]) ^ anchors.view(np.uint64)[fits])
        _, inverse, counts = np.unique(key, return_inverse=True, return_counts=True)
        out[fits[counts[inverse] > 1]] = True
    return out


def _runs(starts: np.ndarray, length: int) -> list[tuple[int, int]]:
    """Covered byte ranges of windows at the starts, which ascend."""
    if not len(starts):
        return []
    cut = np.flatnonzero(np.diff(starts) > length)
    return list(zip(starts[np.r_[0, cut + 1]].tolist(), (starts[np.r_[cut, len(starts) - 1]] + length).tolist()))


def _sort_shards(length: int, budget: int):
    """Rows ordered by anchor; whole anchors are sorted together, at least SHARD bytes at a time."""

    def ranges(held: list) -> pa.RecordBatch:
        out = []
        chance = may_repeat(np.array([x[0] for x in held], dtype=np.int64), [x[3] for x in held], length)
        held = [x for x, may in zip(held, chance) if may]
        for (_, key, start, _), hits in zip(held, repeated_windows([x[3] for x in held], length, budget)):
            out += [(key, start + a, start + b) for a, b in _runs(hits, length)]
        columns = list(zip(*out)) or [(), (), ()]
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["key", "start", "end"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list = []
        size = 0
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if size >= SHARD and row[0] != held[-1][0]:
                    yield ranges(held)
                    held, size = [], 0
                held.append(row)
                size += len(row[3])
        if held:
            yield ranges(held)

    return run


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    text = F.coalesce(F.col(text_col), F.lit(""))
    shape = F.coalesce(F.col(id_col).cast("string"), F.lit("null"))
    return docs.select(F.col(id_col).alias("_id"), text.alias("_text"), F.xxhash64(shape, text).alias("_key"))


def repeated_ranges(docs: DataFrame, length: int = LENGTH, id_col: str = "doc_id", text_col: str = "text", budget: int = 1 << 28) -> DataFrame:
    """(key, start, end): covered byte ranges, which may overlap and repeat; key as in _keyed. A written table; what it
    was made from is deleted."""
    texts = _keyed(docs, id_col, text_col).select("_key", "_text")
    found = texts.where(F.octet_length("_text") >= length).mapInArrow(_emit(length), "anchor long, kind long, key long, start long, end long")
    counts = found.groupBy("anchor").agg(F.count(F.lit(1)).alias("n"), F.min("kind").alias("k0"), F.max("kind").alias("k1"))
    counts = materialise(counts.where("n > 1").select("anchor", (F.col("k0") == F.col("k1")).alias("one")), "repeated-anchors")
    _release(docs.sparkSession)
    meet = materialise(found.join(counts, "anchor"), "repeated-segments")
    _release(docs.sparkSession)
    mixed = meet.where(~F.col("one"))
    kinds = mixed.groupBy("anchor", "kind").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("key", "start", "end")).alias("of"))
    kinds = materialise(kinds.select("anchor", "kind", "n", "of.*"), "segment-kinds")
    # an anchor of one kind twice is in `one`; of several kinds, those seen twice are repeated as a whole
    many = kinds.where("n > 1").select("anchor", "kind")
    whole = meet.where("one").select("key", "start", "end").unionByName(mixed.join(many, ["anchor", "kind"], "left_semi").select("key", "start", "end"))
    hot = kinds.groupBy("anchor").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") > HOT).select("anchor")
    hot = materialise(hot, "hot-anchors")
    calm = kinds.join(hot, "anchor", "left_anti")
    rows = _read(texts, calm).mapInArrow(_pieces(length, False), "anchor long, key long, start long, raw binary")
    rows = rows.repartition("anchor").sortWithinPartitions("anchor", "key", "start")
    out = whole.unionByName(rows.mapInArrow(_sort_shards(length, budget), "key long, start long, end long"))
    used = [counts, meet, kinds, hot]
    if hot.limit(1).count():
        cut = _read(texts, kinds.join(hot, "anchor", "left_semi")).mapInArrow(_pieces(length, True), "a long, b long, key long, start long, n long")
        cut = materialise(cut, "hot-windows")
        twice = materialise(cut.groupBy("a", "b").agg(F.sum("n").alias("m")).where("m > 1").select("a", "b"), "hot-repeats")
        out = out.unionByName(cut.join(twice, ["a", "b"], "left_semi").select("key", "start", (F.col("start") + length).alias("end")))
        used += [cut, twice]
    out = materialise(out, "repeated-ranges")
    discard(*used)
    return out


def _read(texts: DataFrame, wanted: DataFrame) -> DataFrame:
    """(_key, _text, want): each text with its wanted segments; equal rows share a key and repeat each other anyway."""
    want = wanted.groupBy("key").agg(F.collect_list(F.struct("anchor", "start", "end", "n")).alias("want"))
    return texts.join(want, F.col("_key") == F.col("key")).select("_key", "_text", "want")


def _release(spark: SparkSession) -> None:
    """Lets Spark's cleaner delete the shuffle files of steps that are done."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def keep(raw: bytes, ranges: list[tuple[int, int]]) -> tuple[bytes, int, int]:
    """What is left of a text, the bytes removed and the maximal removed runs."""
    out, at, removed, runs, end = [], 0, 0, 0, -1
    for a, b in sorted(ranges):
        if a > end:
            runs += 1
            out.append(raw[at:a])
            removed += b - a
        elif b > end:
            removed += b - end
        end = max(end, b)
        at = end
    out.append(raw[at:])
    return b"".join(out), removed, runs


def _removed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for text, ranges in zip(batch.column(1), batch.column(2)):
            raw = text.as_py().encode()
            left, removed, runs = keep(raw, [(r["start"], r["end"]) for r in ranges.as_py() or []])
            rows.append((len(raw), removed, runs, hashlib.sha256(left).hexdigest(), left))
        columns = list(zip(*rows)) or [()] * 5
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])


def suffix_dedup(docs: DataFrame, length: int = LENGTH, id_col: str = "doc_id", text_col: str = "text", budget: int = 1 << 28) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept): kept is the remaining bytes."""
    if length <= ANCHOR:
        raise ValueError(f"the length must exceed {ANCHOR}")
    ranges = repeated_ranges(docs, length, id_col, text_col, budget)
    _release(docs.sparkSession)
    held = ranges.groupBy("key").agg(F.collect_set(F.struct("start", "end")).alias("_ranges"))
    both = _keyed(docs, id_col, text_col).join(held, F.col("_key") == F.col("key"), "left")
    return both.select(F.col("_id").cast("long").alias("doc_id"), "_text", "_ranges").mapInArrow(_removed, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup(table(spark, sf_dir, "documents")).drop("kept")
