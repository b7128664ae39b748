"""Token-id blocks for training: best-fit-decreasing packing, cumulative segment lengths and position resets.

Each whole text becomes ids once, written to the shared folder. Documents over the window are cut into whole windows
and a remainder, losslessly. Best-fit-decreasing looks at lengths alone, so it runs on the histogram: a segment tree
over the capacities left finds the best open window, whole runs of equal windows at a time, and gives the same
windows as placing the pieces one by one. Pieces find their place by rank (see fill_plan); then each window's pieces
meet by sequence id, a bounded group, and become one row of the id matrix.

Defined results: null or empty text is the ending id alone; repeated rows are packed each for itself; an empty table
gives an empty table; only the id and text columns are read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from poslp.llm.common import materialise, table
from poslp.llm.fill_plan import best_fit_decreasing, histogram, place
from poslp.llm.tokens import END_ID, document_ids, encoder

WINDOW = 2048
BLOCK = "sequence_id long, n_tokens long, cu_seqlens array<int>, doc_ids array<long>, starts array<long>, ids binary"
DIGEST = ", ids_crc32 long, positions_crc32 long"


def _cut(window: int, vocabulary: str | None, width: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, squeeze = encoder(vocabulary), zstandard.ZstdCompressor(level=1)
        uid = TaskContext.get().partitionId() << 33
        for batch in _slices(batches, 512):
            doc, start, length, raw = [], [], [], []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                ids = document_ids(text.as_py(), encode)
                if ids.max() > np.iinfo(width).max:
                    raise ValueError(f"id {ids.max()} does not fit the width {width}")
                ids = ids.astype(width)
                for s in range(0, len(ids), window):
                    part = ids[s : s + window]
                    doc.append(doc_id)
                    start.append(s)
                    length.append(len(part))
                    raw.append(squeeze.compress(part.tobytes()))
            n, uid = uid, uid + len(doc)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(n, uid)), pa.array(doc, pa.int64()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(raw, pa.binary())], names=["uid", "doc_id", "start", "length", "ids"])

    return run


def _slices(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    """The same rows in smaller batches, so that a worker holds little at a time."""
    for batch in batches:
        for s in range(0, batch.num_rows, rows):
            yield batch.slice(s, rows)


def positions(cu: np.ndarray, window: int) -> np.ndarray:
    """Positions of a sequence: from 0 in each segment, and in the padding."""
    begin = np.r_[cu, window] if cu[-1] < window else cu
    return np.arange(window) - np.repeat(begin[:-1], np.diff(begin))


def _assemble(window: int, width: str, digest: bool):
    """Rows ordered by (sequence_id, offset) to one row a sequence; ids padded with the ending id to the window;
    digest: with the CRC-32s of ids and positions as little-endian uint32."""
    pad = np.full(window, END_ID, dtype=width).tobytes()
    kinds = [pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary()] + [pa.int64()] * (2 * digest)
    names = [c.split()[0] for c in (BLOCK + DIGEST * digest).split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spread, held = zstandard.ZstdDecompressor(), []

        def row(parts: list) -> tuple:
            ends = np.cumsum([0, *(p[4] for p in parts)])
            raw = b"".join(spread.decompress(p[5]) for p in parts)
            raw += pad[len(raw) :]
            out = parts[0][0], int(ends[-1]), ends.tolist(), [p[2] for p in parts], [p[3] for p in parts], raw
            if digest:
                out += zlib.crc32(np.frombuffer(raw, width).astype("<u4").tobytes()), zlib.crc32(positions(ends, window).astype("<u4").tobytes())
            return out

        def pack(out: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=names)

        for batch in _slices(batches, 512):
            out = []
            for part in zip(*(c.to_pylist() for c in batch.columns)):
                if held and held[0][0] != part[0]:
                    out.append(row(held))
                    held = []
                held.append(part)
            if out:
                yield pack(out)
        if held:
            yield pack([row(held)])

    return run


def token_blocks(docs: DataFrame, window: int = WINDOW, vocabulary: str | None = None, width: str = "<u2", id_col: str = "doc_id", text_col: str = "text", digest: bool = False) -> DataFrame:
    """One row a sequence: the padded ids (little-endian, ``width``: two bytes hold vocabularies up to 65,536), the
    cumulative segment lengths from 0, and each segment's document and first id in it. An id beyond the width raises."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    # a piece's uid is fixed once the table is written
    cut = materialise(texts.mapInArrow(_cut(window, vocabulary, width), "uid long, doc_id long, start long, length long, ids binary"), "id-pieces")
    counts = histogram(cut, window)
    placed = place(cut.drop("ids"), counts, best_fit_decreasing(counts, window), ["doc_id", "start", "uid"])
    both = cut.join(materialise(placed.select("uid", "sequence_id", "offset"), "id-places"), "uid")
    rows = both.select("sequence_id", "offset", "doc_id", "start", "length", "ids").repartition("sequence_id").sortWithinPartitions("sequence_id", "offset")
    return rows.mapInArrow(_assemble(window, width, digest), BLOCK + DIGEST * digest)


def write_blocks(blocks: DataFrame, path: str, width: str = "<u2") -> None:
    """A parquet sink of the id matrix: fixed-length id rows with their cumulative lengths, positions as a second matrix."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = [positions(np.array(cu.as_py()), len(raw.as_py()) // np.dtype(width).itemsize).astype(width).tobytes() for cu, raw in zip(batch.column(2), batch.column(5))]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(at, pa.binary())], names=[*batch.schema.names, "position_ids"])

    blocks.mapInArrow(run, BLOCK + ", position_ids binary").write.parquet(path)


def op9_token_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The blocks with unsigned CRC-32s of the padded ids and of the positions, each as little-endian uint32."""
    return token_blocks(table(spark, sf_dir, "documents"), digest=True)
