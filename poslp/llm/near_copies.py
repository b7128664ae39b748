"""Near copies: SimHash links, confirmed and completed by exact similarity. The result is the components of texts whose
sets of five-word shingles have Jaccard 0.8 or more.

Fingerprints of the shingles are linked by anchor-point covering (see simhash) and each link is confirmed on the sets.
Texts that similar can differ by a dozen bits, beyond any covering, so what is left is found by prefixes: a pair that similar shares a shingle among the first n - ceil(0.8 n) + 1 of either set, whatever order all sets are
sorted in, so candidates are the pairs that meet at such a shingle (the anchor). No pair is lost, and the order only
decides how many needless candidates there are: by hash, with the shingles that a sample of texts has often put last.
A bitmap of each set bounds what a pair can share from above; candidates within that bound are confirmed on the
whole sets.

Equal sets collapse to one node first. An anchor with few nodes proposes all its pairs. In a larger one each node first
meets its neighbour in size and the smallest node it may resemble; once those links and those of the fingerprints have
joined components, every pair of the anchor that is still apart and within the bound is proposed. So a large group of near
copies costs about as many comparisons as it has members, and the result is that of comparing all pairs.

Defined results: texts of fewer than five words have one shingle of all words; null and wordless texts are copies of each
other; rows without a doc_id take no part. Shingles and sets are told apart by 64-bit hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from poslp.llm.common import ascii_lower, discard, materialise, words
from poslp.llm.components import connected_components
from poslp.llm.simhash import linked_fingerprints, majority_bits

SHINGLE = 5
#: The least similarity as a fraction of whole numbers, so that no rounding decides.
LEAST = (4, 5)
#: Anchors of up to this many nodes propose all their pairs at once.
SMALL = 8
#: One text in SAMPLE is looked at for frequent shingles, of which FREQUENT are put last; they decide cost, not results.
SAMPLE = 64
FREQUENT = 100_000
#: Texts whose sets a Python worker sorts at a time.
ROWS = 256
#: Times the size of the sets that one round of confirming carries through its join.
ROUND = 1
#: Bits of the bitmaps of small and of the largest sets; between them the power of two that is at least twice the set, as a
#: bitmap that is mostly ones bounds nothing. All are powers of two, so a longer one folds onto a shorter one.
BITS, MOST_BITMAP = 1 << 10, 1 << 15


def shingles(w: Column) -> Column:
    """The hashes of all runs of SHINGLE words."""
    runs = F.transform(F.sequence(F.lit(0), F.size(w) - SHINGLE), lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(SHINGLE)]))
    return F.when(F.size(w) >= SHINGLE, runs).when(F.size(w) > 0, F.array(F.xxhash64(w))).otherwise(F.array().cast("array<bigint>"))


def _shingled(docs: DataFrame) -> DataFrame:
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), words(ascii_lower(F.col("text"))).alias("_w"))
    return found.where(F.col("doc_id").isNotNull()).select("doc_id", shingles(F.col("_w")).alias("_s"))


def _lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(row, value) of an array column without nulls."""
    at = column.offsets.to_numpy()
    return np.repeat(np.arange(len(column)), np.diff(at)), column.values.to_numpy(zero_copy_only=False)[at[0] : at[-1]]


def _as_lists(row: np.ndarray, value: np.ndarray, rows: int) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.searchsorted(row, np.arange(rows + 1)).astype(np.int32)), pa.array(value))


def _sets(row: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.lexsort((value, row))
    row, value = row[order], value[order]
    first = np.r_[True, (row[1:] != row[:-1]) | (value[1:] != value[:-1])] if len(row) else np.empty(0, dtype=bool)
    return row[first], value[first]


def _widths(n: np.ndarray) -> np.ndarray:
    """The bits of the bitmaps of sets of n."""
    return np.clip(1 << np.ceil(np.log2(np.maximum(2 * n, 1))).astype(np.int64), BITS, MOST_BITMAP)


def _anchors(often: np.ndarray):
    """often: frequent shingles, the most frequent first."""
    by_value = np.argsort(often, kind="stable")
    sorted_ = often[by_value]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(k, ROWS) for whole in batches for k in range(0, whole.num_rows, ROWS)):
            rows = batch.num_rows
            row, value = _sets(*_lists(batch.column(1)))
            n = np.bincount(row, minlength=rows)
            fp = majority_bits(value, np.searchsorted(row, np.arange(rows + 1)))
            width = _widths(n)
            end = np.cumsum(width)
            seen = np.zeros(end[-1] if rows else 0, dtype=bool)
            seen[(end - width)[row] + (value & (width[row] - 1))] = True
            packed = np.packbits(seen).tobytes()
            bits = pa.array([packed[(e - w) // 8 : e // 8] for e, w in zip(end.tolist(), width.tolist())], pa.binary())
            late = np.zeros(len(value), dtype=np.int64)
            if len(sorted_):
                at = np.minimum(np.searchsorted(sorted_, value), len(sorted_) - 1)
                late = np.where(sorted_[at] == value, len(sorted_) - by_value[at], 0)
            order = np.lexsort((value, late, row))
            row, value = row[order], value[order]
            place = np.arange(len(row)) - np.searchsorted(row, row)
            p, q = LEAST
            mine = place < n[row] + 1 + (-p * n[row]) // q
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n.astype(np.int32)), batch.column(2), pa.array(fp), bits, _as_lists(row[mine], value[mine], rows)], names=["doc_id", "n", "key", "fp", "bits", "anchors"])

    return run


def _grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
    """The columns of rows ordered by the first, cut where it changes, so that each value stands in one part."""
    held: list[list[np.ndarray]] = []
    for batch in batches:
        cols = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
        if not len(cols[0]):
            continue
        cut = int(np.searchsorted(cols[0], cols[0][-1]))
        if cut or (held and held[0][0][0] != cols[0][0]):
            part = [*held, [c[:cut] for c in cols]]
            yield [np.concatenate(x) for x in zip(*part)]
            held = []
        held.append([c[cut:] for c in cols])
    if held:
        yield [np.concatenate(x) for x in zip(*held)]


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for anchor, node, n in _grouped(batches):
        same = anchor[1:] == anchor[:-1]
        keep = np.r_[False, same] | np.r_[same, False]
        yield pa.RecordBatch.from_arrays([pa.array(x[keep]) for x in (anchor, node, n)], names=["anchor", "node", "n"])


def _alike(n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Whether sets of n <= m shingles can be similar."""
    return LEAST[1] * n.astype(np.int64) >= LEAST[0] * m.astype(np.int64)


def _pairs(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    pair = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1), axis=0)
    return pa.RecordBatch.from_arrays([pa.array(pair[:, 0]), pa.array(pair[:, 1])], names=["a", "b"])


def _first_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows in order of anchor, n and node: all pairs of small anchors, two links a node of large ones."""
    for anchor, node, n in _grouped(batches):
        begin = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]])
        count = np.diff(np.r_[begin, len(anchor)])
        size = np.repeat(count, count)
        a, b = [], []
        for k in range(1, SMALL):
            i = np.flatnonzero((anchor[k:] == anchor[:-k]) & _alike(n[:-k], n[k:]) & ((size[k:] <= SMALL) | (k == 1)))
            a.append(node[i])
            b.append(node[i + k])
        for g in np.flatnonzero(count > SMALL):
            of, m = node[begin[g] : begin[g] + count[g]], n[begin[g] : begin[g] + count[g]].astype(np.int64)
            least = np.searchsorted(m, -(-LEAST[0] * m // LEAST[1]))
            a.append(of[least][least < np.arange(len(of))])
            b.append(of[least < np.arange(len(of))])
        yield _pairs(np.concatenate(a), np.concatenate(b))


def _apart(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows in order of anchor, n and node, of large anchors: every pair that is not yet joined and may be similar by its
    sizes and bitmaps."""
    for anchor, node, n, part, bits in _grouped(batches):
        begin = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]])
        for s, e in zip(begin, np.r_[begin[1:], len(anchor)]):
            of, m, p = node[s:e], n[s:e].astype(np.int64), part[s:e]
            if (p == p[0]).all():
                continue
            seen = _Bitmaps(bits[s:e])
            for at in range(0, len(of), 256):
                left = slice(at, at + 256)
                i, j = np.nonzero((p[left, None] != p[None, :]) & _alike(m[left, None], m[None, :]) & (np.arange(len(of))[left, None] < np.arange(len(of))[None, :]))
                i += at
                for k in range(0, len(i), 4096):
                    a, b = i[k : k + 4096], j[k : k + 4096]
                    keep = seen.within(a, b, m)
                    if keep.any():
                        yield _pairs(of[a[keep]], of[b[keep]])


class _Bitmaps:
    """Bitmaps of several widths; two are compared at the lesser of their widths."""

    def __init__(self, column):
        self.width = np.array([8 * len(x) for x in column], dtype=np.int64)
        self.own, self.place = {}, np.zeros(len(self.width), dtype=np.int64)
        for w in np.unique(self.width).tolist():
            mine = np.flatnonzero(self.width == w)
            self.place[mine] = np.arange(len(mine))
            self.own[w] = np.frombuffer(b"".join(column[i] for i in mine), dtype=np.uint64).reshape(len(mine), w // 64)

    def at(self, rows: np.ndarray, width: int) -> np.ndarray:
        """Bitmaps of rows at a width that none is below."""
        out = np.empty((len(rows), width // 64), dtype=np.uint64)
        for w in np.unique(self.width[rows]).tolist():
            mine = np.flatnonzero(self.width[rows] == w)
            out[mine] = np.bitwise_or.reduce(self.own[w][self.place[rows[mine]]].reshape(len(mine), w // width, width // 64), axis=1)
        return out

    def within(self, a: np.ndarray, b: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Whether rows a and b, of sets of n[a] and n[b], may be similar."""
        keep, width = np.zeros(len(a), dtype=bool), np.minimum(self.width[a], self.width[b])
        for w in np.unique(width).tolist():
            mine = np.flatnonzero(width == w)
            step = max(1, 4096 * BITS // w)
            for part in (mine[k : k + step] for k in range(0, len(mine), step)):
                keep[part] = _within(self.at(a[part], w), self.at(b[part], w), n[a[part]], n[b[part]])
        return keep


def _within(x: np.ndarray, y: np.ndarray, n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Whether bitmaps x and y of sets of n and m allow the similarity: what two sets share has a common bit, or is one
    of several on a bit."""
    p, q = LEAST
    ones = lambda z: np.bitwise_count(z).sum(axis=1, dtype=np.int64)
    both = ones(x & y) + np.minimum(n - ones(x), m - ones(y))
    return q * both >= p * (n + m - both)


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    p, q = LEAST
    for batch in batches:
        keep = np.zeros(batch.num_rows, dtype=bool)
        (s, t) = (batch.column(k) for k in (2, 3))
        sa, ta = s.offsets.to_numpy(), t.offsets.to_numpy()
        sv, tv = s.values.to_numpy(zero_copy_only=False), t.values.to_numpy(zero_copy_only=False)
        for k in range(batch.num_rows):
            x, y = sv[sa[k] : sa[k + 1]], tv[ta[k] : ta[k + 1]]
            both = len(np.intersect1d(x, y, assume_unique=True))
            keep[k] = q * both >= p * (len(x) + len(y) - both)
        yield pa.RecordBatch.from_arrays([c.filter(pa.array(keep)) for c in batch.columns[:2]], names=["a", "b"])


def _possible(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = batch.num_rows
        both = _Bitmaps([*batch.column(2).to_pylist(), *batch.column(3).to_pylist()])
        n = np.concatenate([batch.column(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in (4, 5)])
        keep = pa.array(both.within(np.arange(rows), np.arange(rows) + rows, n))
        yield pa.RecordBatch.from_arrays([c.filter(keep) for c in batch.columns[:2]], names=["a", "b"])


def _unique(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        row, value = _sets(*_lists(batch.column(1)))
        yield pa.RecordBatch.from_arrays([batch.column(0), _as_lists(row, value, batch.num_rows)], names=["node", "s"])


def possible(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """Of pairs (a, b) of nodes those whose bitmaps allow the similarity."""
    of = lambda c: nodes.select(F.col("node").alias(c), F.col("bits").alias(f"bits_{c}"), F.col("n").alias(f"n_{c}"))
    near = pairs.join(of("a"), "a").join(of("b"), "b").select("a", "b", "bits_a", "bits_b", "n_a", "n_b")
    return materialise(near.mapInArrow(_possible, "a long, b long"), "possible")


def whole_sets(pairs: DataFrame, docs: DataFrame, nodes: DataFrame) -> DataFrame:
    """(node, s): the sets of the nodes in pairs, each once; nodes: (node, doc_id, ...)."""
    asked = materialise(pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct().join(nodes, "node").select("node", "doc_id"), "asked-nodes")
    found = _shingled(docs.join(asked.select("doc_id").distinct(), "doc_id", "left_semi"))
    found = found.select(F.xxhash64(F.array_sort(F.array_distinct("_s"))).alias("node"), "_s").join(asked.select("node"), "node", "left_semi").dropDuplicates(["node"])
    sets = materialise(found.mapInArrow(_unique, "node long, s array<long>"), "asked-sets")
    discard(asked)
    return sets


def confirmed(pairs: DataFrame, sets: DataFrame, nodes: DataFrame) -> DataFrame:
    """Of pairs (a, b) of nodes, a written table, those that are similar. A pair carries a whole set through the join, so
    the pairs go in rounds that carry about ROUND times what the sets take."""
    sizes = nodes.select(F.col("node").alias("a"), "n")
    carried = pairs.join(sizes, "a").agg(F.sum("n")).first()[0] or 0
    stored = sets.select("node").join(nodes.select("node", "n"), "node").agg(F.sum("n")).first()[0] or 0
    rounds = max(1, -(-carried // max(1, ROUND * stored)))
    out = None
    for k in range(rounds):
        some = pairs.where(F.pmod(F.xxhash64("a", "b"), F.lit(rounds)) == k)
        both = some.join(sets.select(F.col("node").alias("a"), F.col("s").alias("sa")), "a").join(sets.select(F.col("node").alias("b"), F.col("s").alias("sb")), "b")
        one = materialise(both.select("a", "b", "sa", "sb").mapInArrow(_confirm, "a long, b long"), "similar")
        out = one if out is None else out.unionByName(one)
    return out


def joining(pairs: DataFrame, docs: DataFrame, nodes: DataFrame) -> DataFrame:
    """Similar pairs among pairs (a, b), a written table, that have the components of all its similar pairs. Each node's
    first pair is looked at before the others, of which those that are joined by then need no look."""
    sets = whole_sets(pairs, docs, nodes)
    ways = pairs.select("a", "b").unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
    first = ways.groupBy("a").agg(F.min("b").alias("b")).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    first = materialise(first, "pairs-to-join")
    links = confirmed(first, sets, nodes)
    parts = materialise(connected_components(links), "joined-so-far")
    of = lambda c: parts.select(F.col("node").alias(c), F.col("component").alias(f"_{c}"))
    rest = pairs.join(first, ["a", "b"], "left_anti").join(of("a"), "a", "left").join(of("b"), "b", "left")
    rest = materialise(rest.where(F.coalesce("_a", "a") != F.coalesce("_b", "b")).select("a", "b"), "pairs-to-join")
    if rest.limit(1).count():
        links = links.unionByName(confirmed(rest, sets, nodes))
    discard(sets, first, parts, rest, pairs)
    return links


def fingerprint_pairs(nodes: DataFrame) -> DataFrame:
    """(a, b): nodes that SimHash links, as a node of each linked fingerprint, and nodes of one fingerprint."""
    first = materialise(nodes.groupBy("fp").agg(F.min("node").alias("first")), "first-of-print")
    links = linked_fingerprints(first)
    of = lambda c: first.select(F.col("fp").alias(c), F.col("first").alias(f"_{c}"))
    far = links.join(of("a"), "a").join(of("b"), "b").select(F.col("_a").alias("a"), F.col("_b").alias("b"))
    same = nodes.select("node", "fp").join(first, "fp").where(F.col("node") != F.col("first")).select(F.col("first").alias("a"), F.col("node").alias("b"))
    return far.unionByName(same).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def frequent(docs: DataFrame) -> np.ndarray:
    """Shingles that several texts of the sample hold, the most frequent first; at most FREQUENT reach the driver."""
    some = _shingled(docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(SAMPLE)) == 0)).select(F.explode(F.array_distinct("_s")).alias("h"))
    top = some.groupBy("h").count().where("count > 1").orderBy(F.desc("count"), "h").limit(FREQUENT)
    return np.array([r["h"] for r in top.select("h").collect()], dtype=np.int64)


def near_components(docs: DataFrame) -> DataFrame:
    """(doc_id, component_id) for each row with a doc_id: the least doc_id of its component."""
    found = _shingled(docs).select("doc_id", "_s", F.xxhash64(F.array_sort(F.array_distinct("_s"))).alias("key"))
    placed = materialise(found.mapInArrow(_anchors(frequent(docs)), "doc_id long, n int, key long, fp long, bits binary, anchors array<long>"), "anchors")
    nodes = materialise(placed.groupBy(F.col("key").alias("node")).agg(F.min("doc_id").alias("doc_id"), F.first("n").alias("n"), F.first("fp").alias("fp"), F.first("bits").alias("bits")), "nodes")
    own = placed.join(nodes.select("node", F.col("doc_id").alias("_d")), (F.col("key") == F.col("node")) & (F.col("doc_id") == F.col("_d"))).dropDuplicates(["key"])
    rows = own.select(F.explode("anchors").alias("anchor"), F.col("key").alias("node"), "n")
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    met = rows.repartition(parts, "anchor").sortWithinPartitions("anchor").mapInArrow(_shared, "anchor long, node long, n int")
    met = materialise(met, "shared-anchors")
    order = lambda df: df.repartition(parts, "anchor").sortWithinPartitions("anchor", "n", "node")
    pairs = order(met).mapInArrow(_first_pairs, "a long, b long").unionByName(fingerprint_pairs(nodes)).distinct()
    first = materialise(pairs, "first-pairs")
    links = joining(possible(first, nodes), docs, nodes)
    discard(first)
    joined = materialise(connected_components(links), "first-parts")
    large = met.join(met.groupBy("anchor").count().where(F.col("count") > SMALL).select("anchor"), "anchor", "left_semi")
    split = large.join(joined, "node", "left").select("anchor", "node", "n", F.coalesce("component", "node").alias("part"))
    # anchors within one component have no more to say
    split = materialise(split, "large-anchors")
    several = split.groupBy("anchor").agg(F.min("part").alias("p"), F.max("part").alias("q")).where(F.col("p") != F.col("q")).select("anchor")
    large = split.join(several, "anchor", "left_semi").join(nodes.select("node", "bits"), "node").select("anchor", "node", "n", "part", "bits")
    more = materialise(order(large).mapInArrow(_apart, "a long, b long").distinct(), "pairs-apart")
    if more.limit(1).count():
        links = links.unionByName(joining(more, docs, nodes))
        joined = materialise(connected_components(links), "parts")
    named = nodes.join(joined, "node", "left").select("node", "doc_id", F.coalesce("component", "node").alias("part"))
    named = materialise(named, "node-part")
    least = materialise(named.groupBy("part").agg(F.min("doc_id").alias("component_id")), "part-least")
    named = materialise(named.join(least, "part").select(F.col("node").alias("key"), "component_id"), "node-component")
    out = materialise(placed.select("doc_id", "key").join(named, "key").select("doc_id", "component_id"), "doc-components")
    discard(placed, met, split, more)
    return out
