"""External suffix sorting by induction, with common-prefix values.

A suffix is of small type if it is less than its successor, else of large type; a small suffix after a large one is a
star. Star substrings are sorted and named; the sequence of names is the reduced problem, whose suffixes are ordered by
doubling. From the sorted stars all large suffixes are induced in ascending order, and from those all small ones in
descending order. Both inductions pop (position, common prefix) tuples from a priority queue over (first byte, order of
arrival). The queue keeps a FIFO for each first byte and writes the largest to disk whenever its tuples exceed the
memory budget, so it holds shards far larger than memory; the text can be a memory map. The common prefix of two
neighbours in a bucket is one more than the least common prefix between the suffixes that induced them.

Common prefixes are exact up to ``depth`` bytes and capped there, and so is the order.
"""

from __future__ import annotations

import os
import shutil
import tempfile
from collections.abc import Iterator

import numpy as np


class BucketQueue:
    """A priority queue of (position, common prefix) tuples by (byte, arrival), on disk beyond ``budget`` bytes."""

    def __init__(self, budget: int):
        self.budget, self.used, self.dir = budget, 0, None
        self.parts: list[list] = [[] for _ in range(256)]
        self.held = [0] * 256

    def push(self, byte: int, pos: np.ndarray, lcp: np.ndarray) -> None:
        self.parts[byte].append((pos, lcp))
        self.held[byte] += pos.nbytes + lcp.nbytes
        self.used += pos.nbytes + lcp.nbytes
        while self.used > self.budget:
            self._spill(max(range(256), key=self.held.__getitem__))

    def _spill(self, byte: int) -> None:
        self.dir = self.dir or tempfile.mkdtemp(prefix="induce-")
        pos, lcp = self._join([p for p in self.parts[byte] if not isinstance(p, str)])
        path = os.path.join(self.dir, f"{byte}-{len(self.parts[byte])}-{np.random.default_rng().integers(1 << 60)}.npy")
        np.save(path, np.stack([pos, lcp.astype(pos.dtype)]))
        self.parts[byte] = [p for p in self.parts[byte] if isinstance(p, str)] + [path]
        self.used -= self.held[byte]
        self.held[byte] = 0

    @staticmethod
    def _join(parts: list) -> tuple[np.ndarray, np.ndarray]:
        return np.concatenate([p for p, _ in parts]), np.concatenate([q for _, q in parts])

    def pop(self, byte: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """All tuples of a byte in order of arrival, also those that arrive meanwhile, in blocks."""
        while self.parts[byte]:
            part = self.parts[byte].pop(0)
            if isinstance(part, str):
                pos, lcp = np.load(part)
                os.unlink(part)
                yield pos, lcp.astype(np.int32)
            else:
                same = [part]
                while self.parts[byte] and not isinstance(self.parts[byte][0], str):
                    same.append(self.parts[byte].pop(0))
                n = sum(p.nbytes + q.nbytes for p, q in same)
                self.used -= n
                self.held[byte] -= n
                yield self._join(same)

    def close(self) -> None:
        if self.dir:
            shutil.rmtree(self.dir, ignore_errors=True)


class _Inducer:
    """Pushes the predecessors of a scanned sequence, with the common prefixes that the scan implies."""

    def __init__(self, text: np.ndarray, queue: BucketQueue, depth: int):
        self.text, self.queue, self.depth = text, queue, depth
        self.since = np.full(256, -1, dtype=np.int32)  # least common prefix since the last push to each byte

    def scan(self, pos: np.ndarray, lcp: np.ndarray, byte: int, wanted) -> None:
        before = np.where(pos > 0, self.text[np.maximum(pos, 1) - 1], 0)
        take = np.flatnonzero((pos > 0) & wanted(before, byte))
        to = before[take]
        order = np.argsort(to, kind="stable")
        take, to = take[order], to[order]
        begin = np.flatnonzero(np.r_[True, to[1:] != to[:-1]]) if len(to) else np.empty(0, np.int64)
        lowest = lcp.min() if len(lcp) else self.depth
        least = np.minimum(self.since, lowest)
        for s, e in zip(begin, np.r_[begin[1:], len(to)]):
            b, at = int(to[s]), take[s:e]
            first = min(int(self.since[b]), int(lcp[: at[0] + 1].min()))
            rest = np.minimum.reduceat(lcp[: at[-1] + 1], at[:-1] + 1) if e - s > 1 else np.empty(0, np.int32)
            self.queue.push(b, pos[at] - 1, np.minimum(np.r_[np.int32(first), rest] + 1, self.depth).astype(np.int32))
            least[b] = lcp[at[-1] + 1 :].min() if at[-1] + 1 < len(lcp) else self.depth
        self.since = least


def _words(text: np.ndarray) -> np.ndarray:
    """Eight bytes from each position, as big-endian numbers; zeros beyond the end."""
    wide = np.r_[text, np.zeros(8, np.uint8)]
    out = np.zeros(len(text) + 1, dtype=np.uint64)
    for k in range(8):
        out |= wide[k : k + len(text) + 1].astype(np.uint64) << np.uint64(56 - 8 * k)
    return out


def common_prefix(text: np.ndarray, words: np.ndarray, a: np.ndarray, b: np.ndarray, depth: int) -> np.ndarray:
    """Of the suffixes at a and b, pair by pair, capped at depth; the text's end matches nothing."""
    n = len(text)
    out = np.full(len(a), depth, dtype=np.int32)
    live = np.arange(len(a))
    for k in range(0, depth, 8):
        x, y = words[np.minimum(a[live] + k, n)], words[np.minimum(b[live] + k, n)]
        gap = x ^ y
        lead = np.zeros(len(live), dtype=np.int32)
        top = gap.copy()
        for s in (32, 16, 8):
            zero = (top >> np.uint64(64 - s)) == 0
            lead += np.where(zero, s // 8, 0).astype(np.int32)
            top = np.where(zero, top << np.uint64(s), top)
        differs = gap != 0
        out[live[differs]] = np.minimum(k + lead[differs], depth)
        live = live[~differs]
        if not len(live):
            break
    return np.minimum(out, np.minimum(n - a, n - b)).astype(np.int32)


def _ranks(keys: list[np.ndarray]) -> np.ndarray:
    """Dense ranks of rows by their keys, the first the most significant."""
    order = np.lexsort(keys[::-1])
    new = np.zeros(len(order), dtype=bool)
    for k in keys:
        new[1:] |= k[order[1:]] != k[order[:-1]]
    rank = np.empty(len(order), dtype=np.int64)
    rank[order] = np.cumsum(new)
    return rank


def _sorted_stars(text: np.ndarray, words: np.ndarray, stars: np.ndarray, depth: int) -> np.ndarray:
    """The star positions in order of their suffixes, up to depth bytes."""
    if len(stars) < 2:
        return stars
    length = np.diff(np.r_[stars, len(text)]) + 1

    def word(which: np.ndarray, k: int) -> np.ndarray:
        left = np.clip(length[which] - k, 0, 8).astype(np.uint64)
        # bytes past a star substring rank above all others: of two that agree, the longer is less
        fill = np.where(left >= 8, np.uint64(0), np.uint64(0xFFFFFFFFFFFFFFFF) >> np.minimum(left * np.uint64(8), np.uint64(63)))
        fill = np.where(left == 0, np.uint64(0xFFFFFFFFFFFFFFFF), fill)
        return words[np.minimum(stars[which] + k, len(text))] | fill

    every = np.arange(len(stars))
    rank = _ranks([word(every, 0)])
    k = 8
    while k < length.max() and k < depth + 8:
        counts = np.bincount(rank)
        tied = np.flatnonzero((counts[rank] > 1) & (length > k))
        if not len(tied):
            break
        tied = np.flatnonzero(counts[rank] > 1)
        sub = _ranks([rank[tied], word(tied, k)])
        offset = np.zeros(len(stars), dtype=np.int64)
        offset[tied] = sub
        rank = _ranks([rank, offset])
        k += 8
    # the reduced problem: names in text order, ordered by doubling
    reach, step = int(length.min()) - 1 or 1, 1
    m = len(stars)
    covered = 1
    while rank.max() + 1 < m and covered * max(1, reach) < depth + 8:
        following = np.full(m, -1, dtype=np.int64)
        following[: m - step] = rank[step:]
        rank = _ranks([rank, following])
        step *= 2
        covered *= 2
    return stars[np.argsort(rank, kind="stable")]


def sort_suffixes(text: np.ndarray, depth: int = 200, budget: int = 1 << 28) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(positions, common prefix with the one before) of the suffixes of each first byte, in descending order of the
    bytes. text: uint8 from 1 to 254; the end of the text is less than any byte."""
    n = len(text)
    if not n:
        return
    if int(text.max()) == 255 or int(text.min()) == 0:
        raise ValueError("bytes 0 and 255 are kept for the ends of texts and substrings")
    step = np.sign(text[1:].astype(np.int16) - text[:-1].astype(np.int16))
    where = np.where(step != 0, np.arange(n - 1), n)
    following = np.minimum.accumulate(where[::-1])[::-1]
    small = np.zeros(n, dtype=bool)
    small[:-1] = np.r_[step, 0][np.minimum(following, n - 1)] > 0
    stars = np.flatnonzero(small[1:] & ~small[:-1]) + 1
    words = _words(text)
    stars = _sorted_stars(text, words, stars, depth)
    star_lcp = np.zeros(len(stars), dtype=np.int32)
    if len(stars) > 1:
        star_lcp[1:] = common_prefix(text, words, stars[1:], stars[:-1], depth)
    star_at = np.searchsorted(text[stars], np.arange(257))
    pair = lambda a, b: int(common_prefix(text, words, np.array([a]), np.array([b]), depth)[0])

    rising = BucketQueue(budget // 2)
    falling = BucketQueue(budget // 2)
    large = BucketQueue(budget // 2)
    try:
        inducer = _Inducer(text, rising, depth)
        inducer.scan(np.array([n]), np.zeros(1, np.int32), 0, lambda before, _: np.ones(len(before), dtype=bool))
        for c in range(256):
            last = None
            for pos, lcp in rising.pop(c):
                inducer.scan(pos, lcp, c, lambda before, byte: before >= byte)
                large.push(c, pos, lcp)
                last = int(pos[-1])
            own, own_lcp = stars[star_at[c] : star_at[c + 1]], star_lcp[star_at[c] : star_at[c + 1]].copy()
            if len(own):
                own_lcp[0] = pair(last, int(own[0])) if last is not None else 0
                inducer.scan(own, own_lcp, c, lambda before, byte: before > byte)
        inducer = _Inducer(text, falling, depth)
        for c in range(255, -1, -1):
            blocks, last = [], None
            for pos, lcp in falling.pop(c):
                inducer.scan(pos, lcp, c, lambda before, byte: before <= byte)
                blocks.append((pos, lcp))
                last = int(pos[-1])
            sm, sm_lcp = BucketQueue._join(blocks) if blocks else (np.empty(0, np.int64), np.empty(0, np.int32))
            parts = list(large.pop(c))
            la, la_lcp = BucketQueue._join(parts) if parts else (np.empty(0, np.int64), np.empty(0, np.int32))
            if len(la):
                la_lcp = la_lcp.copy()
                la_lcp[0] = 0
                border = pair(last, int(la[-1])) if last is not None else 0
                inducer.scan(la[::-1], np.r_[la_lcp[1:], np.int32(border)][::-1], c, lambda before, byte: before < byte)
            if len(sm) or len(la):
                up = np.r_[np.int32(border if len(la) and len(sm) else 0), sm_lcp[1:][::-1]] if len(sm) else np.empty(0, np.int32)
                yield np.concatenate([la, sm[::-1]]), np.concatenate([la_lcp, up])
    finally:
        for q in (rising, falling, large):
            q.close()
