"""SimHash near-duplicates with anchor-point covering.

A fingerprint has a bit for each of 64 positions, set where over half the shingle hashes have it set. The shingles
and their hashes are built-in functions; the bits of a document's hashes are summed in Arrow batches. Equal
fingerprints collapse to one before any comparison, so a group of copies costs as much as one document.

Links (at most ``4`` differing bits) are found through anchors: the codewords of two perfect binary Golay codes of
length 23, laid side by side over bits 0-45. Each code covers every word of its block within radius 3. Two
fingerprints within 4 bits have a midpoint at most 2 bits from both; the anchor that covers the midpoint exceeds the
covering radius by a and b bits in the two blocks with a + b <= 2, seen from either. So each fingerprint is
replicated to all anchors whose excesses sum to at most 2 (61 on average of 16.7 million), which loses no link. Each
anchor's fingerprints are compared on all 64 bits: small sets by shifted comparison, larger ones by a breadth-first
search that leaves out what it has reached, so a tight cluster gives a spanning tree and not all its pairs.
Components join through written tables (see components).

Defined results: null or empty text has fingerprint zero and is linked like any other; repeated rows collapse; rows
with a null doc_id get a fingerprint and the component of its other holders, or null; an empty table gives an empty
table; only the id and text columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from poslp.llm.common import ascii_lower, materialise, table, words
from poslp.llm.components import connected_components

BLOCK = 23
RADIUS = 3
#: Generator polynomial of the perfect binary Golay code.
GENERATOR = 0b101011100011
MOST_BITS = 4


def shingle_hashes(found: Column, size: int) -> Column:
    """XXH64 with seed 42 of each run of ``size`` words joined by a space; of all words if there are fewer."""
    n = F.size(found)
    runs = F.transform(F.sequence(F.lit(0), n - size), lambda i: F.xxhash64(F.array_join(F.slice(found, i + 1, size), " ")))
    return F.when(n >= size, runs).when(n > 0, F.array(F.xxhash64(F.array_join(found, " ")))).otherwise(F.array().cast("array<bigint>"))


def majority_bits(hashes: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The fingerprint, as int64, of each run hashes[at[k]:at[k + 1]]; of an empty one zero."""
    weights = np.uint64(1) << np.arange(64, dtype=np.uint64)
    flat = np.ascontiguousarray(hashes).view(np.uint8).reshape(-1, 8)
    out = np.zeros(len(at) - 1, dtype=np.uint64)
    for k in range(len(out)):
        ones, n = np.zeros(64, dtype=np.int64), at[k + 1] - at[k]
        for s in range(at[k], at[k + 1], 65536):
            ones += np.unpackbits(flat[s : min(s + 65536, at[k + 1])], axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
        out[k] = weights[2 * ones > n].sum(dtype=np.uint64)
    return out.view(np.int64)


def _majority(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        hashes = batch.column(1)
        fp = majority_bits(hashes.values.to_numpy(zero_copy_only=False), hashes.offsets.to_numpy())
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp)], names=["doc_id", "fp"])


def fingerprints(docs: DataFrame, shingle: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp): fp is the 64-bit fingerprint as a long."""
    found = docs.select(F.col(id_col).cast("long").alias("doc_id"), words(ascii_lower(F.col(text_col))).alias("_w"))
    return found.select("doc_id", shingle_hashes(F.col("_w"), shingle).alias("_h")).mapInArrow(_majority, "doc_id long, fp long")


@lru_cache(1)
def _patterns() -> list[tuple[np.ndarray, np.ndarray]]:
    """For excess 0, 1 and 2: error patterns ordered by syndrome, and where each syndrome's begin."""
    words_, sizes = [], []
    for w in range(RADIUS + 3):
        words_ += [sum(1 << i for i in c) for c in combinations(range(BLOCK), w)]
        sizes.append(len(words_))
    every = np.array(words_, dtype=np.uint64)
    excess = np.repeat([0, 0, 0, 0, 1, 2], np.diff([0, *sizes]))
    syndrome = _syndrome(every)
    out = []
    for e in range(3):
        mine, s = every[excess == e], syndrome[excess == e]
        order = np.argsort(s, kind="stable")
        out.append((mine[order], np.searchsorted(s[order], np.arange(2049))))
    return out


def _syndrome(x: np.ndarray) -> np.ndarray:
    s = x.copy()
    for i in range(BLOCK - 1, 10, -1):
        s = np.where((s >> np.uint64(i)) & np.uint64(1), s ^ np.uint64(GENERATOR << (i - 11)), s)
    return s.astype(np.int64)


def _ragged(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    ends = np.cumsum(counts)
    return np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - counts - starts, counts)


def anchors(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, anchor): every anchor of each fingerprint."""
    low = np.uint64((1 << BLOCK) - 1)
    halves = fp & low, (fp >> np.uint64(BLOCK)) & low
    near = []
    for x in halves:
        s = _syndrome(x)
        for pattern, at in _patterns():
            counts = at[s + 1] - at[s]
            near.append((np.repeat(np.arange(len(fp)), counts), np.repeat(x, counts) ^ pattern[_ragged(at[s], counts)], counts))
    rows, out = [], []
    for a, b in ((0, 0), (0, 1), (0, 2), (1, 0), (1, 1), (2, 0)):
        row, left, _ = near[a]
        _, right, counts = near[3 + b]
        begin = np.cumsum(counts) - counts
        n = counts[row]
        rows.append(np.repeat(row, n))
        out.append(np.repeat(left, n) | (right[_ragged(begin[row], n)] << np.uint64(BLOCK)))
    return np.concatenate(rows), np.concatenate(out)


def _replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        every = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
        for s in range(0, len(every), 4096):
            fp = every[s : s + 4096]
            row, anchor = anchors(fp)
            yield pa.RecordBatch.from_arrays([pa.array(anchor.view(np.int64)), pa.array(fp[row].view(np.int64))], names=["anchor", "fp"])


def _tree(fp: np.ndarray, most: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Spanning trees of the linked fingerprints of one anchor."""
    left, out = fp, []
    while len(left) > 1:
        front, left = left[:1], left[1:]
        while len(front) and len(left):
            part, front = front[:256], front[256:]
            near = np.bitwise_count(part[:, None] ^ left[None, :]) <= most
            hit = near.any(axis=0)
            if hit.any():
                out.append((part[near[:, hit].argmax(axis=0)], left[hit]))
                front, left = np.concatenate([front, left[hit]]), left[~hit]
    return out


def link_sorted(anchor: np.ndarray, fp: np.ndarray, most: int, small: int = 8) -> tuple[np.ndarray, np.ndarray]:
    """Edges among the fingerprints of each anchor; rows are ordered by anchor."""
    begin = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]])
    count = np.diff(np.r_[begin, len(anchor)])
    left, right = [], []
    for k in range(1, small):
        i = np.flatnonzero((anchor[k:] == anchor[:-k]) & (np.bitwise_count(fp[k:] ^ fp[:-k]) <= most))
        left.append(fp[i])
        right.append(fp[i + k])
    for g in np.flatnonzero(count > small):
        for a, b in _tree(fp[begin[g] : begin[g] + count[g]], most):
            left.append(a)
            right.append(b)
    return np.concatenate(left), np.concatenate(right)


def _link(most: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []  # of the last anchor seen, which may go on

        def edges(anchor: np.ndarray, fp: np.ndarray) -> pa.RecordBatch:
            a, b = link_sorted(anchor, fp.view(np.uint64), most)
            pair = np.unique(np.stack([np.minimum(a.view(np.int64), b.view(np.int64)), np.maximum(a.view(np.int64), b.view(np.int64))], axis=1), axis=0)
            return pa.RecordBatch.from_arrays([pa.array(pair[:, 0]), pa.array(pair[:, 1])], names=["a", "b"])

        for batch in batches:
            anchor, fp = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
            if not len(anchor):
                continue
            cut = np.searchsorted(anchor, anchor[-1])
            if cut == 0 and held and held[0][0][0] == anchor[0]:
                held.append((anchor, fp))
                continue
            head = [*held, (anchor[:cut], fp[:cut])]
            yield edges(np.concatenate([x for x, _ in head]), np.concatenate([x for _, x in head]))
            held = [(anchor[cut:], fp[cut:])]
        if held:
            yield edges(np.concatenate([x for x, _ in held]), np.concatenate([x for _, x in held]))

    return run


def linked_fingerprints(distinct: DataFrame, most: int = MOST_BITS) -> DataFrame:
    """(a, b): for each anchor a spanning forest of the links between its fingerprints; distinct: (fp), no repeats."""
    if not 0 <= most <= MOST_BITS:
        raise ValueError("the anchors cover links of up to four bits")
    placed = distinct.select("fp").mapInArrow(_replicate, "anchor long, fp long")
    # about sixty rows for each row that came in
    parts = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return placed.repartition(parts, "anchor").sortWithinPartitions("anchor").mapInArrow(_link(most), "a long, b long").distinct()


def simhash_components(prints: DataFrame, most: int = MOST_BITS) -> DataFrame:
    """(doc_id, fp, component_id) for prints (doc_id, fp); prints should be a written table."""
    first = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("first")), "first-of-print")
    edges = materialise(linked_fingerprints(first, most), "print-links")
    parts = connected_components(edges).withColumnRenamed("node", "fp")
    # every print of a component, with the least doc_id of all
    held = first.join(materialise(parts, "print-parts"), "fp", "left").withColumn("part", F.coalesce("component", "fp"))
    held = materialise(held.select("fp", "part", "first"), "print-part")
    least = materialise(held.groupBy("part").agg(F.min("first").alias("component_id")), "part-least")
    named = materialise(held.join(least, "part").select("fp", "component_id"), "print-component")
    return prints.join(named, "fp").select("doc_id", "fp", "component_id")


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    prints = materialise(fingerprints(table(spark, sf_dir, "documents")), "prints")
    return simhash_components(prints).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
