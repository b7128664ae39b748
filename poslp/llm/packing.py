"""Packing of token pieces into windows by non-negative least squares on the length histogram.

Every combination of up to three lengths that fills the window exactly is a column; the repeat counts that come
closest to the histogram solve a non-negative least-squares problem, are rounded down, and what is left of the
histogram is packed by best-fit-decreasing. The driver sees at most one count per length. Documents longer than the
window are cut into whole windows and a remainder, so each id lies in exactly one piece.

Defined results: null or empty text is the ending id alone; repeated rows are packed each for itself; an empty table
gives an empty table; only the id and text columns are read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from poslp.llm.common import materialise, table
from poslp.llm.fill_plan import best_fit_decreasing, histogram, place
from poslp.llm.tokens import document_ids, encoder

WINDOW = 1024
PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


def _cut(window: int, vocabulary: str | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary)
        for batch in batches:
            out: tuple[list, ...] = ([], [], [], [], [])
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                ids = document_ids(text.as_py(), encode)
                raw = memoryview(ids.astype("<u4").tobytes())
                for s in range(0, len(ids), window):
                    n = min(window, len(ids) - s)
                    for column, value in zip(out, (doc_id, s, n, zlib.crc32(raw[4 * s : 4 * (s + n)]), len(ids))):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return run


def pieces(docs: DataFrame, window: int = WINDOW, vocabulary: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_cut(window, vocabulary), PIECE)


@lru_cache(4)
def combinations_filling(window: int, depth: int = 3) -> np.ndarray:
    """(n, depth) lengths, in falling order and padded with zeros, that sum to the window; shallow: depth 2 or 3."""
    found = [(a, window - a, 0) for a in range(-(-window // 2), window)]
    if depth == 3:
        for a in range(-(-window // 3), window - 1):
            rest = window - a
            found += [(a, b, rest - b) for b in range(-(-rest // 2), min(a, rest - 1) + 1)]
    return np.array(found, dtype=np.int64).reshape(-1, 3)


def non_negative_least_squares(combos: np.ndarray, target: np.ndarray, rounds: int = 60, block: int = 64) -> np.ndarray:
    """Active-set solution of min |A r - target|, r >= 0, where column j of A counts the lengths of combos[j];
    a block of the steepest columns enters at a time and those that turn negative leave."""
    size = len(target)
    real = combos > 0
    push = lambda r: np.bincount(combos[real], weights=np.repeat(r, real.sum(1)), minlength=size)
    pull = lambda v: (v[combos] * real).sum(1)
    r, held = np.zeros(len(combos)), np.zeros(len(combos), dtype=bool)
    best = float(target @ target)
    for _ in range(rounds):
        slope = pull(target - push(r))
        slope[held] = 0
        steep = np.argpartition(-slope, min(block, len(slope) - 1))[:block]
        steep = steep[slope[steep] > 1e-6 * max(1.0, np.abs(target).max())]
        if not len(steep):
            break
        trial = held.copy()
        trial[steep] = True
        while True:
            chosen = np.flatnonzero(trial)
            a = np.zeros((size, len(chosen)))
            np.add.at(a, (combos[chosen].ravel(), np.repeat(np.arange(len(chosen)), 3)), real[chosen].ravel().astype(float))
            x = np.linalg.solve(a.T @ a + 1e-8 * np.eye(len(chosen)), a.T @ target)
            if (x >= 0).all() or not len(chosen):
                break
            trial[chosen[x < 0]] = False
        now = np.zeros(len(combos))
        now[chosen] = x
        gap = push(now) - target
        if (loss := float(gap @ gap)) >= best * (1 - 1e-6):
            break
        r, held, best = now, trial, loss
    return r


def nnls_plan(counts: np.ndarray, window: int) -> list[tuple[tuple[int, ...], int]]:
    """(lengths in a window, windows) for exactly the pieces counted."""
    combos = combinations_filling(window)
    left = counts.astype(np.int64).copy()
    plan = [((window,), int(left[window]))] if left[window] else []
    left[window] = left[0] = 0
    combos = combos[((combos == 0) | (left[combos] > 0)).all(1)]
    if len(combos):
        repeats = np.floor(non_negative_least_squares(combos, left.astype(float)) + 1e-9).astype(np.int64)
        for j in np.argsort(-repeats, kind="stable"):
            lengths = [int(x) for x in combos[j] if x]
            times = min([int(repeats[j]), *(int(left[x]) // lengths.count(x) for x in lengths)])
            if times <= 0:
                continue
            for x in lengths:
                left[x] -= times
            plan.append((tuple(lengths), times))
    return plan + best_fit_decreasing(left, window)


def pack(cut: DataFrame, window: int = WINDOW) -> DataFrame:
    """sequence_id and offset for each row of cut, a written table of pieces."""
    counts = histogram(cut, window)
    return place(cut, counts, nnls_plan(counts, window), ["doc_id", "start", "ids_crc32"])


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = materialise(pieces(table(spark, sf_dir, "documents")), "pieces")
    return pack(cut).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")
