"""Matchings: greedy by least degree, and exact two-sided matching by layered search for augmenting paths."""

from __future__ import annotations

from collections import deque

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from poslp.plans.shared import discard, materialise


def greedy_matching(edges: DataFrame) -> DataFrame:
    """A maximal matching (u, v), in as many rounds as it takes: each removes the least of all edges at least. Each round every vertex proposes along its edge to the least-degree neighbour (vertices
    of degree one come first by that rule); edges that both ends propose are taken, and their vertices leave."""
    left, taken, rounds = edges.select("u", "v"), None, []
    while True:
        ends = left.select(F.explode(F.array("u", "v")).alias("vid")).groupBy("vid").agg(F.count(F.lit(1)).alias("d"))
        ends = materialise(ends, "left-degrees")
        if not ends.limit(1).count():
            break
        before = left
        ranked = left.join(ends.select(F.col("vid").alias("u"), F.col("d").alias("du")), "u").join(ends.select(F.col("vid").alias("v"), F.col("d").alias("dv")), "v")
        key = F.struct((F.least("du", "dv")).alias("a"), (F.col("du") + F.col("dv")).alias("b"), F.xxhash64("u", "v").alias("h"), F.col("u").alias("x"), F.col("v").alias("y"))
        ranked = ranked.select("u", "v", key.alias("k"))
        best = ranked.select(F.explode(F.array("u", "v")).alias("vid"), "k").groupBy("vid").agg(F.min("k").alias("k"))
        both = best.groupBy("k").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") == 2)
        new = materialise(both.select(F.col("k.x").alias("u"), F.col("k.y").alias("v")), "taken")
        taken = new if taken is None else taken.unionByName(new)
        busy = new.select(F.explode(F.array("u", "v")).alias("vid"))
        left = left.join(busy.withColumnRenamed("vid", "u"), "u", "left_anti").join(busy.withColumnRenamed("vid", "v"), "v", "left_anti")
        left = materialise(left, "left-edges")
        rounds.append(new)
        if len(rounds) >= 16:  # few and large tables in place of many small ones
            taken = materialise(taken, "taken")
            discard(*rounds)
            rounds = [taken]
        discard(before, ends)
    return taken if taken is not None else edges.select("u", "v").limit(0)


def augmenting_matching(edges: DataFrame) -> DataFrame:
    """A maximum matching (l, r) of a two-sided graph with even left and odd right vertices.

    From all free left vertices at once, layers alternate between unmatched and matched edges; each right vertex is
    reached once, by the parent of least id. The first layers that reach free right vertices give paths; of the paths
    of one root and of those that share a vertex one is kept, and they are flipped. When none is left, no augmenting
    path exists; each phase adds an edge at least, so phases end by themselves."""
    sided = materialise(edges.select(F.when(F.col("u") % 2 == 0, F.col("u")).otherwise(F.col("v")).alias("l"), F.when(F.col("u") % 2 == 0, F.col("v")).otherwise(F.col("u")).alias("r")), "sided")
    first = greedy_matching(edges)
    match = materialise(first.select(F.when(F.col("u") % 2 == 0, F.col("u")).otherwise(F.col("v")).alias("l"), F.when(F.col("u") % 2 == 0, F.col("v")).otherwise(F.col("u")).alias("r")), "match")
    while True:
        layers, old = [], match
        front = sided.select("l").distinct().join(match, "l", "left_anti").select("l", F.col("l").alias("root"), F.array().cast("array<struct<l:bigint,r:bigint>>").alias("path"))
        seen = match.select("r").limit(0)
        found = None
        while True:
            reach = sided.join(front, "l").join(seen, "r", "left_anti")
            reach = reach.groupBy("r").agg(F.min(F.struct("l", "root", "path")).alias("p")).select("r", "p.root", F.concat("p.path", F.array(F.struct(F.col("p.l").alias("l"), F.col("r")))).alias("path"))
            reach = materialise(reach, "reach")
            layers.append(reach)
            if not reach.limit(1).count():
                break
            ends = reach.join(match, "r", "left_anti")
            if ends.limit(1).count():
                found = ends.groupBy("root").agg(F.min(F.struct("r", "path")).alias("p")).select("p.path")
                break
            seen = materialise(seen.unionByName(reach.select("r")), "seen")
            layers.append(seen)
            front = reach.join(match, "r").select("l", "root", "path")
        if found is None:
            break
        # trees of different roots are disjoint: each right vertex has one parent, so paths of different roots are too
        new = materialise(found.select(F.explode("path").alias("e")).select("e.l", "e.r"), "flipped")
        kept = match.join(new.select("r"), "r", "left_anti").select("l", "r").join(new.select("l"), "l", "left_anti").select("l", "r")
        match = materialise(kept.unionByName(new), "match")
        discard(old, new, *layers)
    return match


#: Entries that are put in order at a time, and times that the edges are gone through for that at most.
ORDERED, PASSES = 1 << 22, 16


def neighbours(ways: list[tuple[np.ndarray, np.ndarray]], n: int) -> tuple[np.ndarray, np.ndarray]:
    """(starts, near): the targets of source i are near[starts[i] : starts[i + 1]], in order; ways: (sources, targets).
    Arrays, since lists of numbers take ten times the memory, and some sources at a time, as numbers to sort by take more."""
    most = max((int(t.max()) + 1 for _, t in ways if len(t)), default=1)
    count = np.zeros(n, dtype=np.int64)
    for source, _ in ways:
        for s in range(0, len(source), ORDERED):
            count += np.bincount(source[s : s + ORDERED], minlength=n)
    starts = np.r_[0, np.cumsum(count)]
    near = np.empty(starts[-1], dtype=np.int32 if most < 1 << 31 else np.int64)
    step = max(ORDERED, -(-len(near) // PASSES))
    low = 0
    while low < n:
        high = max(low + 1, int(np.searchsorted(starts, starts[low] + step, side="right")) - 1)
        keys = []
        for source, target in ways:
            mine = (source >= low) & (source < high)
            key = source[mine].astype(np.int64)
            key *= most
            key += target[mine]
            keys.append(key)
        key = np.concatenate(keys)
        key.sort()
        key %= most
        near[starts[low] : starts[high]] = key
        low = high
    return starts, near


def hopcroft_karp(u: np.ndarray, v: np.ndarray, n: int, left: np.ndarray) -> int:
    """Exact size on the driver, for graphs whose edges fit its memory; left: which vertices are left."""
    forward = left[u]
    starts, near = neighbours([(np.where(forward, u, v), np.where(forward, v, u))], n)
    return _most_pairs(starts, near, n, np.flatnonzero(left).tolist())


def _most_pairs(starts: np.ndarray, near: np.ndarray, n: int, roots: list[int]) -> int:
    """roots: the left vertices; right ones are below n, in numbers of their own or not."""
    begin = starts.tolist()
    mate = [-1] * n  # of right vertices
    free, size = [i for i in roots if begin[i] < begin[i + 1]], 0
    while True:
        dist, queue = dict.fromkeys(free, 0), deque(free)
        end = False
        while queue:
            i = queue.popleft()
            for j in near[begin[i] : begin[i + 1]].tolist():
                k = mate[j]
                if k < 0:
                    end = True
                elif k not in dist:
                    dist[k] = dist[i] + 1
                    queue.append(k)
        if not end:
            return size
        entered, unmatched = set(), []
        for root in free:
            # (vertex, its neighbours that are left, the one taken); only vertices on the path have theirs as a list
            entered.add(root)
            stack = [[root, iter(near[begin[root] : begin[root + 1]].tolist()), -1]]
            while stack:
                top = stack[-1]
                i = top[0]
                for j in top[1]:
                    k = mate[j]
                    if k < 0 or dist.get(k) == dist[i] + 1 and k not in entered:
                        top[2] = j
                        break
                else:
                    stack.pop()
                    continue
                if k < 0:
                    for p, _, q in stack:
                        mate[q] = p
                    size += 1
                    break
                entered.add(k)
                stack.append([k, iter(near[begin[k] : begin[k + 1]].tolist()), -1])
            else:
                unmatched.append(root)
        free = unmatched


def double_cover_value(u: np.ndarray, v: np.ndarray, n: int) -> float:
    """The exact fractional matching (and cover) value: half the matching of the two-sided double cover."""
    return _most_pairs(*neighbours([(u, v), (v, u)], n), n, list(range(n))) / 2
