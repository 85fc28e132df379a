"""Numpy kernels: mutual information from nearest neighbours, its incremental form, and other estimators."""

from __future__ import annotations

import heapq
from functools import lru_cache

import numpy as np

EULER = 0.5772156649015329


@lru_cache(maxsize=8)
def _harmonic(n: int) -> np.ndarray:
    return np.r_[0.0, np.cumsum(1.0 / np.arange(1, n + 1))]


def digamma_int(m) -> np.ndarray:
    """Digamma of positive integers: harmonic sums less Euler's constant."""
    m = np.asarray(m)
    size = 1 << max(10, int(m.max(initial=1)).bit_length())
    return _harmonic(size)[m - 1] - EULER


def jitter(v: np.ndarray, salt: int) -> np.ndarray:
    """Breaks ties by noise of a millionth of the spread, fixed by position."""
    noise = np.random.default_rng(salt).random(len(v)) - 0.5
    return v + noise * 1e-6 * (v.std() or 1.0)


def smallest(d, at, size):
    """Of each row of distances d, to points `at`, the `size` smallest in order; ties go to the smaller point.

    Rows with fewer are filled up with infinite distances to a point beyond all.
    """
    n = d.shape[1]
    if size < n <= 2 * size:
        near, who = d, at
    elif n > size:
        part = np.argpartition(d, size - 1, axis=1)[:, :size]
        near, who = np.take_along_axis(d, part, 1), np.take_along_axis(at, part, 1)
        tied = np.flatnonzero((d <= near.max(1)[:, None]).sum(1) > size)
        if len(tied):
            order = np.lexsort((at[tied], d[tied]), axis=1)[:, :size]
            near[tied], who[tied] = np.take_along_axis(d[tied], order, 1), np.take_along_axis(at[tied], order, 1)
    else:
        near, who = d, at
    order = np.lexsort((who, near), axis=1)[:, :size]
    row = np.arange(len(order))[:, None]
    near, who = near[row, order], who[row, order]
    if n < size:
        fill = ((0, 0), (0, size - n))
        near, who = np.pad(near, fill, constant_values=np.inf), np.pad(who, fill, constant_values=BEYOND)
    who[np.isinf(near)] = BEYOND
    return near, who


def matrix_nearest(x, y, rows, size, block=512):
    """Distances to and indices of the nearest `size` of each of the given points, against all points."""
    out = []
    for b in range(0, len(rows), block):
        p = rows[b : b + block]
        d = np.maximum(np.abs(x[p, None] - x), np.abs(y[p, None] - y))
        d[np.arange(len(p)), p] = np.inf
        out.append(smallest(d, np.broadcast_to(np.arange(len(x)), d.shape), size))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True)) if out else (np.zeros((0, size)), np.zeros((0, size), np.int64))


class Boxes:
    """Points in equal boxes, sorted by box; the boxes around many points are looked at together.

    A column of neighbouring boxes is one stretch of the sorted points, so that a square of boxes is a few stretches. A
    point is settled when its last distance does not reach beyond the square; the others go on with a square twice as wide.
    """

    MOST = 1 << 21

    def __init__(self, x, y, per_box=3):
        self.x, self.y, n = x, y, len(x)
        wide, high = np.ptp(x), np.ptp(y)
        longest = max(wide, high, 1e-300)
        self.side = max((wide * high * per_box / n) ** 0.5, longest * per_box / n, longest * 1e-6)
        self.cx, self.cy = ((v - v.min()) // self.side for v in (x, y))
        self.cx, self.cy = self.cx.astype(np.int64), self.cy.astype(np.int64)
        self.columns, self.rows = int(self.cx.max()) + 1, int(self.cy.max()) + 1
        key = self.cx * self.rows + self.cy
        self.order = np.argsort(key, kind="stable")
        self.keys = key[self.order]

    def _around(self, p, ring):
        """Candidates of the points p: a row each, padded, with their distances."""
        cols = self.cx[p, None] + np.arange(-ring, ring + 1)
        inside = (cols >= 0) & (cols < self.columns)
        low, high = np.maximum(self.cy[p] - ring, 0), np.minimum(self.cy[p] + ring, self.rows - 1)
        cols = np.clip(cols, 0, self.columns - 1) * self.rows
        s = np.searchsorted(self.keys, cols + low[:, None], side="left")
        e = np.where(inside, np.searchsorted(self.keys, cols + high[:, None], side="right"), s)
        many = (e - s).sum(1)
        width = int(many.max())
        flat_s, flat_n = s.ravel(), (e - s).ravel()
        total = int(flat_n.sum())
        at = np.arange(total) - np.repeat(np.cumsum(flat_n) - flat_n, flat_n) + np.repeat(flat_s, flat_n)
        row = np.repeat(np.arange(len(p)), many)
        col = np.arange(total) - np.repeat(np.cumsum(many) - many, many)
        who = np.full((len(p), width), BEYOND, np.int64)
        who[row, col] = self.order[at]
        d = np.full((len(p), width), np.inf)
        j = self.order[at]
        d[row, col] = np.where(j == p[row], np.inf, np.maximum(np.abs(self.x[p[row]] - self.x[j]), np.abs(self.y[p[row]] - self.y[j])))
        return d, who

    def nearest(self, rows, size):
        near, who = np.empty((len(rows), size)), np.empty((len(rows), size), np.int64)
        waiting, ring = np.arange(len(rows)), 1 + (size > 9)
        while len(waiting):
            whole, later = ring >= max(self.columns, self.rows), []
            block = max(1, self.MOST // (len(self.x) if whole else min(len(self.x), 4 * (2 * ring + 1) ** 2 * 3)))
            for b in range(0, len(waiting), block):
                w = waiting[b : b + block]
                if whole:
                    near[w], who[w] = matrix_nearest(self.x, self.y, rows[w], size)
                    continue
                near[w], who[w] = smallest(*self._around(rows[w], ring), size)
                later.append(w[~(near[w, -1] < ring * self.side * (1 - 1e-9))])
            waiting, ring = np.concatenate(later) if later else waiting[:0], ring * 2
        return near, who


#: The index of no point, and the size of a window from which on its points are put into boxes.
BEYOND, BOXED = np.iinfo(np.int64).max, 1024


def nearest(x, y, rows, size):
    """By boxes where there are many points, else by the whole matrix of distances; the result is the same."""
    return Boxes(x, y).nearest(rows, size) if len(x) >= BOXED and len(rows) else matrix_nearest(x, y, rows, size)


def extents_of(x, y, near, who):
    """Of each point: distance to the k-th, extents over all k and of the k-th alone."""
    dx, dy = np.abs(x[who] - x[:, None]), np.abs(y[who] - y[:, None])
    return near[:, -1], dx.max(1), dy.max(1), dx[:, -1], dy[:, -1]


def brute(x, y, k):
    return extents_of(x, y, *matrix_nearest(x, y, np.arange(len(x)), k))


class Tree:
    """A k-d tree of points, searched best first."""

    def __init__(self, x, y, leaf=16):
        self.p = np.stack([x, y], 1)
        self.root = self._build(np.arange(len(x)), leaf)

    def _build(self, ids, leaf):
        low, high = self.p[ids].min(0), self.p[ids].max(0)
        if len(ids) <= leaf or (low == high).all():
            return low, high, ids, None
        axis = int((high - low).argmax())
        o = ids[np.argsort(self.p[ids, axis], kind="stable")]
        m = len(o) // 2
        return low, high, None, (self._build(o[:m], leaf), self._build(o[m:], leaf))

    def nearest(self, i: int, k: int) -> np.ndarray:
        q, best, heap, turn = self.p[i], [], [(0.0, 0, self.root)], 0
        while heap:
            bound, _, (_, _, ids, kids) = heapq.heappop(heap)
            if len(best) == k and bound > -best[0][0]:
                break
            if ids is not None:
                d = np.abs(self.p[ids] - q).max(1)
                for dist, j in zip(d.tolist(), ids.tolist(), strict=True):
                    if j != i:
                        (heapq.heappush if len(best) < k else heapq.heappushpop)(best, (-dist, -j))
                continue
            for kid in kids:
                turn += 1
                gap = np.maximum(np.maximum(kid[0] - q, q - kid[1]), 0).max()
                heapq.heappush(heap, (float(gap), turn, kid))
        return np.array([-j for _, j in sorted(best, reverse=True)])


def projected(x, y, k):
    """Neighbours by sorting on x and widening both ways until the distance in x alone is too far."""
    o = np.argsort(x, kind="stable")
    xs, ys, out = x[o], y[o], []
    n = len(x)
    for p in range(n):
        far = k
        while True:
            a, b = max(0, p - far), min(n, p + far + 1)
            d = np.maximum(np.abs(xs[a:b] - xs[p]), np.abs(ys[a:b] - ys[p]))
            d[p - a] = np.inf
            near = np.lexsort((o[a:b], d))[:k]
            edge = min(xs[p] - xs[a] if a else np.inf, xs[b - 1] - xs[p] if b < n else np.inf)
            if len(d) > k and (d[near[-1]] < edge or (a == 0 and b == n)):
                out.append((o[p], o[a + near]))
                break
            far *= 2
    return dict(out)


def extents(x, y, k, search="brute"):
    if search == "brute":
        return brute(x, y, k)
    if search == "box":
        return extents_of(x, y, *Boxes(x, y).nearest(np.arange(len(x)), k))
    if search == "projection":
        by = projected(x, y, k)
        near = np.stack([by[i] for i in range(len(x))])
    else:
        tree = Tree(x, y)
        near = np.stack([tree.nearest(i, k) for i in range(len(x))])
    dx, dy = np.abs(x[near] - x[:, None]), np.abs(y[near] - y[:, None])
    d = np.maximum(dx, dy)
    one, last = np.arange(len(x)), d.shape[1] - 1 - np.argmax(d[:, ::-1], axis=1)
    return d.max(1), dx.max(1), dy.max(1), dx[one, last], dy[one, last]


def within(sorted_values, values, reach):
    """How many others lie within reach of each value."""
    a = np.searchsorted(sorted_values, values - reach, side="left")
    b = np.searchsorted(sorted_values, values + reach, side="right")
    return b - a - 1


def counted(ordered, v, reach):
    """How many other values lie within reach, by their places in the ordered values; as exact as comparing differences."""
    n = len(ordered)
    low, high = np.searchsorted(ordered, v - reach, side="left"), np.searchsorted(ordered, v + reach, side="right")
    while (m := (low > 0) & (v - ordered[low - 1] <= reach)).any():  # sums are rounded: mend by differences
        low[m] = np.searchsorted(ordered, ordered[low[m] - 1], side="left")
    while (m := (low < n) & (v - ordered[np.minimum(low, n - 1)] > reach)).any():
        low[m] = np.searchsorted(ordered, ordered[low[m]], side="right")
    while (m := (high < n) & (ordered[np.minimum(high, n - 1)] - v <= reach)).any():
        high[m] = np.searchsorted(ordered, ordered[high[m]], side="right")
    while (m := (high > 0) & (ordered[high - 1] - v > reach)).any():
        high[m] = np.searchsorted(ordered, ordered[high[m] - 1], side="left")
    return high - low - 1


def knn_mi(x, y, k=6, extent="max_k", variant=2, search="brute", tie=None) -> float | None:
    """Mutual information in nats. variant 1 has one radius and strict counts; extent 'kth' takes the k-th point alone."""
    x, y = np.asarray(x, float), np.asarray(y, float)
    n = len(x)
    if n <= k:
        return None
    if tie == "jitter":
        x, y = jitter(x, 1), jitter(y, 2)
    d, dx, dy, kx, ky = extents(x, y, k, search)
    if variant == 1:
        nx, ny = ((np.abs(v[:, None] - v) < d[:, None]).sum(1) - 1 for v in (x, y))
        return float(digamma_int(np.array(k)) - (digamma_int(nx + 1) + digamma_int(ny + 1)).mean() + digamma_int(np.array(n)))
    if extent == "kth":
        dx, dy = kx, ky
    nx, ny = counted(np.sort(x), x, dx), counted(np.sort(y), y, dy)
    return from_counts(nx, ny, k, n)


def from_counts(nx, ny, k, n) -> float:
    return float(digamma_int(np.array(k)) - 1 / k - (digamma_int(np.maximum(nx, 1)) + digamma_int(np.maximum(ny, 1))).mean() + digamma_int(np.array(n)))


class IncrementalKnn:
    """The estimator's state for a window that slides: only points that a change can touch are looked at again.

    Every point keeps a list of its nearest neighbours, more than k, in order, and the distance up to which the list is
    whole. Points that leave the window leave the lists; points that come are put into the lists that they fall into.
    A point is searched anew, by boxes, only when its list has fewer than k left. Marginal counts follow from the sorted
    values of the window. The result equals that of a window that starts from nothing.

    region 'square' takes a newcomer into a list by its distance, which is exact; 'rect' only where it lies within the
    point's extents on both axes, and misses neighbours. counters: 'researched' are points of whose k neighbours one left
    or came, 'recounted' others with another marginal count, 'rebuilt' those searched anew.
    """

    def __init__(self, x, y, k=6, region="square", spare=None):
        self.x, self.y, self.k, self.region = np.asarray(x, float), np.asarray(y, float), k, region
        n, self.size = len(self.x), k + (k + 4 if spare is None else spare)
        self.near, self.who = np.full((n, self.size), np.inf), np.full((n, self.size), BEYOND, np.int64)
        self.whole, self.last = np.full(n, np.inf), np.full(n, BEYOND, np.int64)
        self.dx, self.dy = np.zeros(n), np.zeros(n)
        self.nx, self.ny = np.zeros(n, np.int64), np.zeros(n, np.int64)
        self.s = self.e = 0
        self.counters = dict.fromkeys(("windows", "added", "removed", "researched", "recounted", "untouched", "rebuilt"), 0)

    @property
    def d(self):
        """The distance of each point to its k-th neighbour."""
        return self.near[:, self.k - 1]

    def _bound(self, at) -> None:
        """A full list is whole up to its last entry, one that has all points of the window up to any distance."""
        self.whole[at], self.last[at] = self.near[at, -1], self.who[at, -1]

    def _search(self, at: np.ndarray) -> None:
        s, e = self.s, self.e
        near, who = nearest(self.x[s:e], self.y[s:e], at - s, self.size)
        self.near[at], self.who[at] = near, np.where(who == BEYOND, BEYOND, who + s)
        self._bound(at)

    def _leave(self, stay: slice) -> np.ndarray:
        """Takes what has left the window out of the lists; which points have lost one of their k."""
        who = self.who[stay]
        gone = ((who < self.s) | (who >= self.e)) & (who != BEYOND)
        rows = np.flatnonzero(gone.any(1))
        if len(rows):
            order = np.argsort(gone[rows], axis=1, kind="stable")
            at, out = rows + stay.start, np.take_along_axis(gone[rows], order, 1)
            near, who = np.take_along_axis(self.near[at], order, 1), np.take_along_axis(self.who[at], order, 1)
            near[out], who[out] = np.inf, BEYOND
            self.near[at], self.who[at] = near, who
        return gone[:, : self.k].any(1)

    def _enter(self, stay: slice, come: np.ndarray) -> np.ndarray:
        """Puts newcomers into the lists that they fall into; which points have got one of their k."""
        changed = np.zeros(stay.stop - stay.start, bool)
        for b in range(0, len(come), 512):
            p = come[b : b + 512]
            ax, ay = np.abs(self.x[stay, None] - self.x[p]), np.abs(self.y[stay, None] - self.y[p])
            d = np.maximum(ax, ay)
            whole = self.whole[stay, None]
            inside = (d < whole) | ((d == whole) & (p < self.last[stay, None]))
            if self.region == "rect":
                inside &= (ax <= self.dx[stay, None]) & (ay <= self.dy[stay, None])
            rows = np.flatnonzero(inside.any(1))
            if not len(rows):
                continue
            at, kth = rows + stay.start, self.who[rows + stay.start, : self.k]
            r, c = np.nonzero(inside[rows])  # few for each row: put side by side
            many = np.bincount(r, minlength=len(rows))
            place = self.size + np.arange(len(r)) - np.repeat(np.cumsum(many) - many, many)
            every, who = (np.full((len(rows), self.size + int(many.max())), f) for f in (np.inf, BEYOND))
            every[:, : self.size], who[:, : self.size] = self.near[at], self.who[at]
            every[r, place], who[r, place] = d[rows[r], c], p[c]
            over = at[many + np.isfinite(every[:, : self.size]).sum(1) > self.size]  # something falls out at the far end
            self.near[at], self.who[at] = near, who = smallest(every, who, self.size)
            self._bound(over)
            changed[rows] |= (who[:, : self.k] != kth).any(1)
        return changed

    def _count(self, at: np.ndarray) -> None:
        s, e = self.s, self.e
        who = self.who[at, : self.k]
        self.dx[at], self.dy[at] = np.abs(self.x[who] - self.x[at, None]).max(1), np.abs(self.y[who] - self.y[at, None]).max(1)
        self.nx[s:e] = counted(np.sort(self.x[s:e]), self.x[s:e], self.dx[s:e])
        self.ny[s:e] = counted(np.sort(self.y[s:e]), self.y[s:e], self.dy[s:e])

    def slide(self, s: int, e: int) -> float | None:
        c, k = self.counters, self.k
        c["windows"] += 1
        a, b = max(s, self.s), min(e, self.e)
        old = (self.s, self.e)
        self.s, self.e = s, e
        if b - a <= k or e - s <= k:
            c["added"] += e - s
            if e - s <= k:
                self.s = self.e = s
                return None
            self._search(np.arange(s, e))
            self._count(np.arange(s, e))
            return from_counts(self.nx[s:e], self.ny[s:e], k, e - s)
        stay, come = slice(a, b), np.r_[s:a, b:e]
        nx, ny = self.nx[stay].copy(), self.ny[stay].copy()
        moved = self._leave(stay) | self._enter(stay, come)
        short = np.flatnonzero(np.isinf(self.near[stay, k - 1])) + a
        self._search(np.concatenate([short, come]).astype(np.int64))
        moved[short - a] = True
        self._count(np.concatenate([np.flatnonzero(moved) + a, come]).astype(np.int64))
        other = ~moved & ((self.nx[stay] != nx) | (self.ny[stay] != ny))
        c["added"] += len(come)
        c["removed"] += (a - old[0]) + (old[1] - b)
        c["rebuilt"] += len(short)
        c["researched"] += int(moved.sum())
        c["recounted"] += int(other.sum())
        c["untouched"] += int((~moved & ~other).sum())
        return from_counts(self.nx[s:e], self.ny[s:e], k, e - s)

    def state_bytes(self) -> int:
        return sum(a.nbytes for a in (self.near, self.who, self.whole, self.last, self.dx, self.dy, self.nx, self.ny))


def bins_for(n: int) -> int:
    return max(3, round((n / 5) ** 0.5))


def equal_width(v, bins, low=None, high=None):
    v = np.asarray(v, float)
    low, high = (v.min() if low is None else low), (v.max() if high is None else high)
    if high == low:
        return np.zeros(len(v), int)
    return np.clip(np.floor((v - low) / (high - low) * bins), 0, bins - 1).astype(int)


def plugin(bx, by) -> dict:
    """Entropies and mutual information of binned or categorical values, in nats."""
    n = len(bx)
    _, ix = np.unique(bx, return_inverse=True)
    _, iy = np.unique(by, return_inverse=True)
    h = []
    for codes in (ix, iy, ix * (iy.max(initial=0) + 1) + iy):
        p = np.unique(codes, return_counts=True)[1] / n
        h.append(float(-(p * np.log(p)).sum()))
    return {"hx": h[0], "hy": h[1], "hxy": h[2], "mi": max(0.0, h[0] + h[1] - h[2])}


def direction(x, y) -> dict:
    """Steps in the same and in opposite directions, the degree, its label, and the label's confidence."""
    dx, dy = np.sign(np.diff(x)), np.sign(np.diff(y))
    pp, np_, n = int((dx * dy > 0).sum()), int((dx * dy < 0).sum()), len(x)
    mu = (pp - np_) / (n - 1) if n > 1 else None
    sign = None if mu is None else "positive" if mu > 0 else "negative" if mu < 0 else "neither"
    top, base = {"positive": (pp - np_, pp), "negative": (np_ - pp, np_), "neither": (n - 1 - pp - np_, n - 1), None: (0, 0)}[sign]
    return {"pp": pp, "np": np_, "mu": mu, "sign": sign, "conf": top / base if base else None}


def score(x, y, estimator="knn", k=6, bins=None, mi=None, tie="jitter") -> dict:
    """A window's whole row of measures."""
    x, y = np.asarray(x, float), np.asarray(y, float)
    n = len(x)
    bins = bins or bins_for(n)
    h = plugin(equal_width(x, bins), equal_width(y, bins))
    if estimator == "auto":
        estimator = "plugin" if min(len(np.unique(x)), len(np.unique(y))) < 0.5 * n else "knn"
    value = h["mi"] if estimator == "plugin" else mi if mi is not None else knn_mi(x, y, k, tie=tie)
    log_n = np.log(n) if n > 1 else None
    return {"n": n, "mi": value, "hx": h["hx"], "hy": h["hy"], "hxy": h["hxy"], "h_norm": h["hxy"] / log_n if log_n else None, "mi_norm1": value / log_n if log_n and value is not None else None, "mi_norm2": value / h["hxy"] if h["hxy"] and value is not None else None} | direction(x, y)


def dcor(x, y, block=1024) -> float | None:
    """Distance correlation, by blocks of rows."""
    x, y = np.asarray(x, float), np.asarray(y, float)
    n = len(x)
    if n < 2:
        return None
    mx, my = (np.concatenate([np.abs(v[b : b + block, None] - v).mean(1) for b in range(0, n, block)]) for v in (x, y))
    xy = xx = yy = 0.0
    for b in range(0, n, block):
        a = np.abs(x[b : b + block, None] - x) - mx[b : b + block, None] - mx + mx.mean()
        c = np.abs(y[b : b + block, None] - y) - my[b : b + block, None] - my + my.mean()
        xy, xx, yy = xy + (a * c).sum(), xx + (a * a).sum(), yy + (c * c).sum()
    return float((max(xy, 0) / (xx * yy) ** 0.5) ** 0.5) if xx * yy > 0 else 0.0


def kde_mi(x, y, bandwidth=None, block=512) -> float:
    """Mutual information from Gaussian kernel densities, each point left out of its own."""
    x, y = ((v - v.mean()) / (v.std() or 1) for v in (np.asarray(x, float), np.asarray(y, float)))
    n = len(x)
    h = bandwidth or 1.06 * n ** (-1 / 6)
    total = 0.0
    for b in range(0, n, block):
        kx, ky = np.exp(-(((x[b : b + block, None] - x) / h) ** 2) / 2), np.exp(-(((y[b : b + block, None] - y) / h) ** 2) / 2)
        i = np.arange(b, min(n, b + block))
        kx[i - b, i] = ky[i - b, i] = 0
        fx, fy, fxy = kx.sum(1), ky.sum(1), (kx * ky).sum(1)
        total += np.log(np.maximum(fxy * (n - 1), 1e-300) / np.maximum(fx * fy, 1e-300)).sum()
    return float(total / n)


def permutation_quantile(x, y, measure, alpha=0.01, reps=99, seed=0) -> float:
    """The (1 - alpha) quantile of a measure under shuffling."""
    rng = np.random.default_rng(seed)
    return float(np.quantile([measure(x, rng.permutation(y)) for _ in range(reps)], 1 - alpha))


def total_correlation(columns, bins=None) -> float:
    """Of more than two variables: the sum of their entropies less the joint one, binned."""
    bins = bins or bins_for(len(columns[0]))
    codes = [equal_width(c, bins) for c in columns]
    h = 0.0
    for c in codes:
        p = np.unique(c, return_counts=True)[1] / len(c)
        h -= (p * np.log(p)).sum()
    p = np.unique(np.stack(codes, 1), axis=0, return_counts=True)[1] / len(codes[0])
    return float(h + (p * np.log(p)).sum())


def top_down(x, y, start, end, layers, accept_of, **options):
    """All layers, coarse to fine, over [start, end): a finer layer has the spans that the coarser ones left.

    layers: (size, step) pairs. Returns (layer, row) of what is selected, the spans left at last, and counters by layer.
    """
    spans, chosen, tallies = [(start, end)], [], []
    for i, (size, step) in enumerate(layers):
        left, tally = [], {}
        for s, e in spans:
            got, rest, counters = scan(x, y, s, e, size, step, accept_of(i), **options)
            chosen += [(i, r) for r in got]
            left += rest
            tally = {c: tally.get(c, 0) + n for c, n in counters.items()}
        tallies.append(tally)
        spans = left
    return chosen, spans, tallies


def scan(x, y, start, end, size, step, accept, k=6, estimator="knn", incremental=True, tie="jitter", region="square", scores=None):
    """One layer over [start, end): take a window that passes and jump past it, shift one that fails.

    Returns (selected rows, left-out spans, counters). Spans are half-open; tails and runs shorter than a window stay left out.
    """
    x, y = (jitter(np.asarray(v, float), i + 1) if tie == "jitter" and estimator == "knn" else np.asarray(v, float) for i, v in enumerate((x, y)))
    kernel = IncrementalKnn(x, y, k, region) if estimator == "knn" and scores is None else None
    chosen, left, free, s, windows = [], [], start, start, 0
    while s + size <= end:
        a, b = s, s + size
        windows += 1
        if scores is not None:
            row = scores(a, b)
        elif kernel is not None:
            if not incremental:
                kernel.s = kernel.e = 0
            row = score(x[a:b], y[a:b], "knn", k, mi=kernel.slide(a, b), tie=None)
        else:
            row = score(x[a:b], y[a:b], estimator, k, tie=tie)
        if accept(row):
            chosen.append({"s": a, "e": b} | row)
            if free < a:
                left.append((free, a))
            s = free = b
            if kernel is not None:
                kernel.s = kernel.e = b
        else:
            s += step
    if free < end:
        left.append((free, end))
    counters = dict(kernel.counters) if kernel is not None else dict.fromkeys(("added", "removed", "researched", "recounted", "untouched", "rebuilt"), 0) | {"windows": windows}
    return chosen, left, counters
