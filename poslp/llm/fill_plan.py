"""Plans that fill windows from a histogram of piece lengths, and their realisation without global sorting.

A plan says which lengths stand together in how many windows. It depends on the histogram alone: at most ``window``
counts reach the driver, whatever the corpus. Pieces of one length are interchangeable, so the plan becomes a table
of rank ranges per length, and each piece finds its place through its rank among the pieces of its length. Ranks are
handed out in two levels, (length, salt) groups with prefix sums of their counts, so that a length which a third of
all pieces share is no hot group.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from poslp.llm.common import materialise

#: Pieces to a (length, salt) group at least, about; the square root of a length's pieces if that is more.
GROUP = 200


def histogram(pieces: DataFrame, window: int) -> np.ndarray:
    """Counts of lengths 0..window; at most window rows reach the driver."""
    out = np.zeros(window + 1, dtype=np.int64)
    for r in pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect():
        out[r["length"]] = r["n"]
    return out


def plan_table(spark, plan: list[tuple[tuple[int, ...], int]]) -> DataFrame:
    """Rank ranges: pieces of ``length`` ranked lo..hi-1 go to sequences first.., each at ``offset``.
    plan: (lengths in a window, windows); its size is bounded by the window, not by the corpus."""
    rows, used, first = [], {}, 0
    for combo, times in plan:
        offset = 0
        for length in combo:
            lo = used.get(length, 0)
            rows.append((int(length), int(lo), int(lo + times), int(first), int(offset)))
            used[length] = lo + times
            offset += length
        first += times
    return spark.createDataFrame(rows, "length long, lo long, hi long, first long, offset long")


def place(pieces: DataFrame, counts: np.ndarray, plan: list[tuple[tuple[int, ...], int]], keys: list[str]) -> DataFrame:
    """pieces with sequence_id and offset. counts: their histogram; keys: columns that order the pieces of a length.
    pieces must be a written table with a long ``length`` from 1; the plan must have a place for each piece."""
    spark = pieces.sparkSession
    salts = F.array(*[F.lit(max(1, int(n) // max(GROUP, int(n**0.5)))) for n in counts])
    salted = pieces.withColumn("_salt", F.pmod(F.xxhash64(*keys), F.get(salts, F.col("length").cast("int"))))
    groups = salted.groupBy("length", "_salt").agg(F.count(F.lit(1)).alias("_n"))
    before = F.sum("_n").over(Window.partitionBy("length").orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1))
    groups = materialise(groups.withColumn("_before", F.coalesce(before, F.lit(0))).drop("_n"), "rank-groups")
    ranked = salted.withColumn("_k", F.row_number().over(Window.partitionBy("length", "_salt").orderBy(*keys)) - 1)
    ranked = ranked.join(groups, ["length", "_salt"]).withColumn("_rank", F.col("_k") + F.col("_before"))
    # one row per length, so no more rows than the window has tokens
    ranges = plan_table(spark, plan).groupBy("length").agg(F.sort_array(F.collect_list(F.struct("lo", "first", "offset"))).alias("_ranges"))
    both = ranked.join(F.broadcast(ranges), "length").withColumn("_at", F.expr("element_at(filter(_ranges, r -> r.lo <= _rank), -1)"))
    both = both.withColumns({"sequence_id": F.col("_at.first") + F.col("_rank") - F.col("_at.lo"), "offset": F.col("_at.offset")})
    return both.drop("_salt", "_k", "_before", "_rank", "_ranges", "_at")


class CapacityTree:
    """Best fit over capacities 1..window: a segment tree of how many open windows have each capacity left."""

    def __init__(self, window: int):
        self.size = 1 << window.bit_length()
        self.tree = [0] * (2 * self.size)

    def add(self, capacity: int, n: int) -> None:
        at = capacity + self.size
        while at:
            self.tree[at] += n
            at >>= 1

    def least(self, need: int) -> int:
        """The smallest capacity >= need that an open window has; 0 if none."""
        at = need + self.size
        if self.tree[at]:
            return need
        while at > 1:
            if not at & 1 and self.tree[at + 1]:
                at += 1
                while at < self.size:
                    at = 2 * at if self.tree[2 * at] else 2 * at + 1
                return at - self.size
            at >>= 1
        return 0


def best_fit_decreasing(counts: np.ndarray, window: int) -> list[tuple[tuple[int, ...], int]]:
    """Best-fit-decreasing of counts[length] pieces, whole runs of equal windows at a time."""
    tree, open_ = CapacityTree(window), {}
    for length in range(window, 0, -1):
        left = int(counts[length])
        while left:
            room = tree.least(length) or window
            combo, n = open_[room].pop() if tree.tree[room + tree.size] else ((), left)
            known = bool(combo)
            each = room // length  # a window just served stays the best fit while the length goes into it
            take, each = (min(n, left // each), each) if left >= each else (1, left)
            if known:
                tree.add(room, -take)
                if take < n:
                    open_[room].append((combo, n - take))
            room -= each * length
            open_.setdefault(room, []).append((combo + (length,) * each, take))
            if room:
                tree.add(room, take)
            left -= take * each
    return [x for same in open_.values() for x in same]
