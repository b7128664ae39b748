"""Pairs of items that stand together under some key, where many items share one: no pair is ever shuffled.

Items are numbered in order. The members of a key go out as one short list for each block of BLOCK items, and each task
holds a run of RUN items with one bitmap of a block for each of them: an item's bitmap is the union of the members of its
keys, so each pair comes out once, however many keys hold it. What moves is each list once for every run, which is far
less than the pairs.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from poslp.plans.shared import materialise

#: Items of a bitmap, a multiple of 64 whose offsets fit a short; items of a run, a divisor of it.
BLOCK, RUN = 1 << 14, 1 << 11
#: Bitmaps that are unpacked into pairs at a time.
ROWS = 32
IDS, BEFORE, MEMBERS = 0, 1, 2


def _units(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, pa.Table]]:
    """The rows of each run and block, which come in order."""
    held, now = [], None
    for batch in batches:
        run, block = (batch.column(k).to_numpy() for k in (0, 1))
        cut = np.flatnonzero(np.r_[True, (run[1:] != run[:-1]) | (block[1:] != block[:-1])]) if len(run) else []
        for s, e in zip(cut, [*cut[1:], len(run)]):
            at = int(run[s]), int(block[s])
            if now is not None and at != now:
                yield *now, pa.Table.from_batches(held)
                held = []
            now = at
            held.append(batch.slice(s, e - s))
    if held:
        yield *now, pa.Table.from_batches(held)


def _unions(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    """(whether a run begins, ids of its items, numbers before them, ids of a block, a bitmap of it for each item with no
    item itself, the block's distance from the run) for each run and block; the run's own block comes first."""
    mine: dict[str, np.ndarray] = {}
    run = None
    for of, block, rows in _units(batches):
        kind, key = rows.column("kind").to_numpy(), rows.column("k").to_pylist()
        ids, at = rows.column("ids").combine_chunks(), rows.column("at").combine_chunks()
        low = of * RUN - block * BLOCK  # the run's place, seen from the block
        begins, block_ids = of != run, None
        lists = []
        for i in range(len(kind)):
            if kind[i] == IDS:
                block_ids = ids[i].values.to_numpy()
            elif kind[i] == BEFORE:
                before = ids[i].values.to_numpy()
            else:
                lists.append((key[i], at[i].values.to_numpy()))
        if begins:
            run, own_ids = of, block_ids[low : low + RUN]
            mine = {k: a[(a >= low) & (a < low + RUN)] - low for k, a in lists}
            mine = {k: a for k, a in mine.items() if len(a)}
            if not (kind == BEFORE).any():
                before = np.zeros(len(own_ids), dtype=np.int64)
        seen = np.zeros((len(own_ids), BLOCK // 8), dtype=np.uint8)
        for k, a in lists:
            if k in mine:
                bits = np.zeros(BLOCK, dtype=bool)
                bits[a] = True
                seen[mine[k]] |= np.packbits(bits, bitorder="little")
        if begins:
            self_ = np.arange(len(own_ids)) + low
            seen[np.arange(len(own_ids)), self_ >> 3] &= ~(np.uint8(1) << (self_ & 7).astype(np.uint8))
        yield begins, own_ids, before, block_ids, seen, low


def _degrees(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for _, own, _, _, seen, _ in _unions(batches):
        n = np.bitwise_count(seen.view(np.uint64)).sum(axis=1, dtype=np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(own[n > 0]), pa.array(n[n > 0])], names=["vid", "n"])


def _later(seen: np.ndarray, low: int) -> np.ndarray:
    """Of bitmaps of items from low on of a block the bits after each item; all of them where the items lie before it."""
    if low < 0:
        return seen
    place = np.arange(len(seen)) + low
    first = np.arange(seen.shape[1])[None, :] - (place >> 3)[:, None]
    part = (0xFF << ((place & 7) + 1)).astype(np.uint8)
    return np.where(first > 0, seen, np.where(first == 0, seen & part[:, None], np.uint8(0)))


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """How many of its pairs each item is the lesser of."""
    for _, own, _, _, seen, low in _unions(batches):
        n = np.bitwise_count(_later(seen, low).view(np.uint64)).sum(axis=1, dtype=np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(own), pa.array(n)], names=["i", "n"])


def _pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for begins, own, before, block, seen, low in _unions(batches):
        next_ = before.copy() if begins else next_
        seen = _later(seen, low)
        n = np.bitwise_count(seen.view(np.uint64)).sum(axis=1, dtype=np.int64)
        for s in range(0, len(own), ROWS):
            i, j = np.nonzero(np.unpackbits(seen[s : s + ROWS], axis=1, bitorder="little"))
            if len(i):
                part = n[s : s + ROWS]
                eid = np.arange(len(i)) + (next_[s : s + ROWS] - np.r_[0, np.cumsum(part)[:-1]])[i]
                yield pa.RecordBatch.from_arrays([pa.array(eid), pa.array(own[s : s + ROWS][i]), pa.array(block[j])], names=["eid", "u", "v"])
        next_ += n


class Together:
    """rows under keys (k, any string; null: none) with items (i, long; null: none)."""

    def __init__(self, rows: DataFrame, key: Column, item: Column):
        from poslp.sources.graphs import with_rank

        rows = rows.select(key.alias("k"), item.cast("long").alias("i")).where(F.col("k").isNotNull() & F.col("i").isNotNull())
        self.items = materialise(with_rank(rows.select("i").distinct(), "i", "r").select("i", (F.col("r") - 1).alias("r")), "items")
        placed = rows.join(self.items, "i")
        block = F.floor(F.col("r") / BLOCK).cast("int").alias("block")
        lists = placed.groupBy("k", block).agg(F.collect_set((F.col("r") % BLOCK).cast("short")).alias("at"))
        names = self.items.groupBy(block).agg(F.array_sort(F.collect_list(F.struct("r", "i")))["i"].alias("ids"))
        kinds = lists.select("block", F.lit(MEMBERS).alias("kind"), "k", "at", F.lit(None).cast("array<bigint>").alias("ids"))
        kinds = kinds.unionByName(names.select("block", F.lit(IDS).alias("kind"), F.lit(None).cast("string").alias("k"), F.lit(None).cast("array<smallint>").alias("at"), "ids"))
        self.lists = materialise(kinds, "member-lists")
        self.runs = -(-self.items.count() // RUN)
        self.parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def _dealt(self, all_blocks: bool, before: DataFrame | None = None) -> DataFrame:
        """(run, block, kind, k, at, ids): each block for every run, or for the runs that lie in it or before it."""
        last = F.lit(self.runs - 1) if all_blocks else F.least(F.lit(self.runs - 1), (F.col("block") + 1) * (BLOCK // RUN) - 1)
        rows = self.lists.select(F.explode(F.sequence(F.lit(0), last.cast("int"))).alias("run"), "block", "kind", "k", "at", "ids")
        if before is not None:
            rows = rows.unionByName(before)
        own = F.floor(F.col("run") * RUN / BLOCK) != F.col("block")
        rows = rows.repartition(max(1, min(self.runs, max(self.parts, 200))), "run")
        return rows.sortWithinPartitions("run", own, "block", "kind").select("run", "block", "kind", "k", "at", "ids")

    def degrees(self) -> DataFrame:
        """(vid, degree)."""
        if not self.runs:
            return self.items.select(F.col("i").alias("vid"), F.col("r").alias("degree"))
        return self._dealt(True).mapInArrow(_degrees, "vid long, n long").groupBy("vid").agg(F.sum("n").alias("degree"))

    def _begun(self) -> DataFrame:
        """The number of pairs before each item's own, as a list for each run."""
        counts = self._dealt(False).mapInArrow(_counts, "i long, n long").groupBy("i").agg(F.sum("n").alias("n"))
        run = F.floor(F.col("r") / RUN).cast("int").alias("run")
        counts = materialise(counts.join(self.items, "i").select(run, "r", "n"), "pairs-by-item")
        whole = counts.groupBy("run").agg(F.sum("n").alias("_n"))
        # one row a run
        start = F.coalesce(F.sum("_n").over(Window.orderBy("run").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        inside = F.coalesce(F.sum("n").over(Window.partitionBy("run").orderBy("r").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        both = counts.withColumn("_in", inside).join(F.broadcast(whole.select("run", start.alias("_start"))), "run")
        listed = both.groupBy("run").agg(F.array_sort(F.collect_list(F.struct("r", (F.col("_start") + F.col("_in")).alias("b"))))["b"].alias("ids"))
        block = F.floor(F.col("run") * RUN / BLOCK).cast("int").alias("block")
        return materialise(listed.select("run", block, F.lit(BEFORE).alias("kind"), F.lit(None).cast("string").alias("k"), F.lit(None).cast("array<smallint>").alias("at"), "ids"), "pairs-before")

    def numbered(self) -> DataFrame:
        """(eid, u, v): u < v, each pair once, eid its rank from 0."""
        if not self.runs:
            return self.items.select(F.col("i").alias("eid"), F.col("i").alias("u"), F.col("i").alias("v"))
        return self._dealt(False, self._begun()).mapInArrow(_pairs, "eid long, u long, v long")

    def pairs(self) -> DataFrame:
        """(u, v): u < v, each pair once."""
        if not self.runs:
            return self.items.select(F.col("i").alias("u"), F.col("i").alias("v"))
        return self._dealt(False).mapInArrow(_pairs, "eid long, u long, v long").select("u", "v")
