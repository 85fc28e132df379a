"""Suffix sorting by induction over bucket queues that go to disk when they outgrow their memory.

Suffixes that are smaller than their right neighbour and follow one that is larger are sorted first, by the symbols up to
the next of their kind; equal ones are named alike and their order is found one level up. From them all others follow:
a queue holds, for each first symbol, suffixes in their final order, and taking a symbol's suffixes pushes their left
neighbours. Pushes never go back behind the symbol that is being taken, so that the queue is a monotone priority queue
of first-in-first-out buckets, which may lie on disk: each is written and read once, in order.
"""

from __future__ import annotations

import tempfile

import numpy as np


class BucketQueue:
    """First symbol to positions, first in, first out; arrays beyond `most` bytes go to a temporary file."""

    def __init__(self, symbols: int, most: int):
        self.parts: list[list] = [[] for _ in range(symbols)]
        self.most, self.size, self.file = most, 0, None

    def push(self, chars: np.ndarray, values: np.ndarray) -> None:
        """In the order given, each to the bucket of its symbol."""
        order = np.argsort(chars, kind="stable")
        chars, values = chars[order], values[order]
        cuts = np.flatnonzero(chars[1:] != chars[:-1]) + 1
        for s, e in zip([0, *cuts.tolist()], [*cuts.tolist(), len(chars)], strict=True):
            self.parts[chars[s]].append(values[s:e])
        self.size += values.nbytes
        if self.size > self.most:
            self._spill()

    def _spill(self) -> None:
        if self.file is None:
            self.file = tempfile.TemporaryFile()
        self.file.seek(0, 2)
        for parts in self.parts:
            for i, p in enumerate(parts):
                if isinstance(p, np.ndarray):
                    parts[i] = (self.file.tell(), len(p), p.dtype)
                    self.file.write(np.ascontiguousarray(p).tobytes())
        self.size = 0

    def take(self, symbol: int) -> np.ndarray | None:
        parts, self.parts[symbol] = self.parts[symbol], []
        if not parts:
            return None
        out = []
        for p in parts:
            if isinstance(p, np.ndarray):
                self.size -= p.nbytes
            else:
                self.file.seek(p[0])
                p = np.frombuffer(self.file.read(p[1] * p[2].itemsize), p[2])
            out.append(p)
        return np.concatenate(out)

    def close(self) -> None:
        if self.file is not None:
            self.file.close()


def doubled(names: np.ndarray) -> np.ndarray:
    """The order of the suffixes of a short string of many symbols, comparing twice as far each time."""
    n = len(names)
    _, rank = np.unique(names, return_inverse=True)
    far = 1
    while True:
        beyond = np.zeros(n, np.int64)
        if far < n:
            beyond[:-far] = rank[far:] + 1
        key = rank.astype(np.int64) * (n + 1) + beyond
        order = np.argsort(key, kind="stable")
        new = np.zeros(n, np.int64)
        new[order[1:]] = np.cumsum(key[order[1:]] != key[order[:-1]])
        rank = new
        if n == 0 or rank[order[-1]] == n - 1:
            return order
        far *= 2


def named(t: np.ndarray, small: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Equal names for equal substrings from each of `at` to the next, in the order of the substrings."""
    size = np.diff(at, append=len(t) - 1) + 1
    symbol = np.zeros(len(t) + 6, np.uint64)
    symbol[: len(t)] = t.astype(np.uint64) * np.uint64(2) + small
    rank, active, far = np.zeros(len(at), np.int64), np.arange(len(at)), 0
    while len(active):
        key = np.zeros(len(active), np.uint64)
        left = size[active] - far
        for j in range(6):
            key = (key << np.uint64(10)) | np.where(left > j, symbol[np.minimum(at[active] + far + j, len(t))], np.uint64(0))
        order = np.lexsort((key, rank[active]))
        r, k = rank[active][order], key[order]
        place = np.arange(len(order))
        old = np.r_[True, r[1:] != r[:-1]]
        sub = old | np.r_[True, k[1:] != k[:-1]]
        rank[active[order]] = r + place[np.maximum.accumulate(np.where(sub, place, 0))] - place[np.maximum.accumulate(np.where(old, place, 0))]
        far += 6
        active = active[size[active] > far]
    return rank


def suffix_array(text: np.ndarray, symbols: int = 257, most: int = 64 << 20) -> np.ndarray:
    """The sorted suffixes of text, whose symbols are under 511; one that is smaller than all is put at its end."""
    t = np.r_[text.astype(np.int32) + 1, np.int32(0)]
    symbols, n = symbols + 1, len(t)
    up, same = t[:-1] < t[1:], t[:-1] == t[1:]
    decides = np.minimum.accumulate(np.where(same, n, np.arange(n - 1))[::-1])[::-1] if n > 1 else np.zeros(0, int)
    small = np.r_[up[np.minimum(decides, max(n - 2, 0))], True] if n > 1 else np.array([True])
    seeds = np.flatnonzero(small[1:] & ~small[:-1]) + 1
    if not len(seeds):
        seeds = np.array([n - 1])
    names = named(t, small, seeds)
    seeds = seeds[doubled(names)].astype(np.int32)
    seed_symbol = t[seeds]
    bounds = np.searchsorted(seed_symbol, np.arange(symbols + 1))

    def induce(queue: BucketQueue, now: np.ndarray, symbol: int, want: bool) -> np.ndarray | None:
        p = now[now > 0] - 1
        p = p[small[p] == want]
        c = t[p]
        here = c == symbol
        if len(p) and not here.all():
            queue.push(c[~here], p[~here])
        return p[here]

    large: list[np.ndarray] = []
    queue = BucketQueue(symbols, most)
    for s in range(symbols):
        mine, now = [], queue.take(s)
        while now is not None and len(now):
            mine.append(now)
            now = induce(queue, now, s, False)
        large.append(np.concatenate(mine) if mine else np.zeros(0, np.int32))
        if bounds[s + 1] > bounds[s]:
            induce(queue, seeds[bounds[s] : bounds[s + 1]], s, False)
    queue.close()
    out: list[np.ndarray] = []
    queue = BucketQueue(symbols, most)
    for s in range(symbols - 1, -1, -1):
        mine, now = [], queue.take(s)
        while now is not None and len(now):
            mine.append(now)
            now = induce(queue, now, s, True)
        if len(large[s]):
            induce(queue, large[s][::-1], s, True)
        if mine:
            out.append(np.concatenate(mine))
        out.append(large[s][::-1])
    queue.close()
    return np.concatenate([*out])[::-1]
