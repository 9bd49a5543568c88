"""Array kernels that run inside Arrow batches, keyed state and single-task experiment cells.

A window is summarised by unweighted sums per (batch, cluster); fading weights are applied to those few rows afterwards, so
one pass serves every forget parameter and every error that weights whole batches.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np


def nearest(x: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Index of the nearest centroid (the lowest of equals) and the squared distance to it.

    One matrix product finds candidates; rows whose two best are closer than rounding can tell are settled by differences.
    """
    if len(x) == 0:
        return np.empty(0, dtype=np.int64), np.empty(0)
    mid = c.mean(axis=0)
    a, b = x - mid, c - mid
    d = (a * a).sum(axis=1)[:, None] - 2.0 * (a @ b.T) + (b * b).sum(axis=1)[None, :]
    k = d.argmin(axis=1)
    if len(c) > 1:
        two = np.partition(d, 1, axis=1)[:, :2]
        scale = (a * a).sum(axis=1) + (b * b).sum(axis=1).max() + 1e-300
        close = np.flatnonzero(two[:, 1] - two[:, 0] <= 1e-9 * scale)
        for i in close.tolist():
            k[i] = ((x[i] - c) ** 2).sum(axis=1).argmin()
    return k, ((x - c[k]) ** 2).sum(axis=1)


def nearest_two(x: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The two nearest centroids and the margin between their squared distances."""
    d = ((x[:, None, :] - c[None, :, :]) ** 2).sum(axis=2)
    order = np.argsort(d, axis=1, kind="stable")[:, :2]
    rows = np.arange(len(x))
    return order[:, 0], order[:, 1], d[rows, order[:, 1]] - d[rows, order[:, 0]]


@dataclass
class Sums:
    """n, sum of x, sum of |x|^2 and squared error for each (batch, cluster); batches in ascending order."""

    seqs: np.ndarray
    n: np.ndarray
    sx: np.ndarray
    sxx: np.ndarray
    sse: np.ndarray

    @staticmethod
    def zeros(seqs: Sequence[int], k: int, d: int) -> Sums:
        w = len(seqs)
        return Sums(np.array(seqs, dtype=np.int64), np.zeros((w, k)), np.zeros((w, k, d)), np.zeros((w, k)), np.zeros((w, k)))

    def keep(self, mask: np.ndarray) -> Sums:
        return Sums(self.seqs[mask], self.n[mask], self.sx[mask], self.sxx[mask], self.sse[mask])

    @property
    def points(self) -> int:
        return int(self.n.sum())

    def weighted(self, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Weighted counts and sums by cluster."""
        return w @ self.n, np.tensordot(w, self.sx, axes=1)

    def error(self, w: np.ndarray) -> float:
        """Weighted mean of the squared distances; nan for an empty window."""
        mass = float((w[:, None] * self.n).sum())
        return float((w[:, None] * self.sse).sum() / mass) if mass else float("nan")


def sums_of(x: np.ndarray, seq: np.ndarray, c: np.ndarray, weight: np.ndarray | None = None) -> Sums:
    """Sums of the points under centroids c; with weights, n, sx, sxx and sse are weighted."""
    seqs, at = np.unique(seq, return_inverse=True)
    out = Sums.zeros(seqs, len(c), c.shape[1])
    if not len(x):
        return out
    k, d2 = nearest(x, c)
    w = np.ones(len(x)) if weight is None else weight
    cell = at * len(c) + k
    size = len(seqs) * len(c)
    out.n = np.bincount(cell, w, size).reshape(out.n.shape)
    out.sse = np.bincount(cell, w * d2, size).reshape(out.n.shape)
    out.sxx = np.bincount(cell, w * (x * x).sum(axis=1), size).reshape(out.n.shape)
    out.sx = np.stack([np.bincount(cell, w * x[:, j], size) for j in range(x.shape[1])], axis=1).reshape(out.sx.shape)
    return out


class Packed:
    """A small window of narrow points, laid out once for all its passes: sums(c) equals sums_of(x, seq, c)."""

    #: Rows and coordinates up to which a pass is ruled by the calls it makes, not by the points.
    ROWS, WIDTH = 20_000, 8

    def __init__(self, x: np.ndarray, seq: np.ndarray) -> None:
        self.x, self.columns = x, np.arange(x.shape[1] + 3)
        self.seqs, self.at = np.unique(seq, return_inverse=True)
        self.mid = x.mean(axis=0)
        self.xt, self.rows = np.ascontiguousarray(x.T), np.arange(len(x))
        self.a = self.xt - self.mid[:, None]
        self.aa = (self.a * self.a).sum(axis=0)
        self.load = np.column_stack([np.ones(len(x)), x, (x * x).sum(axis=1), np.zeros(len(x))])

    def nearest(self, c: np.ndarray) -> np.ndarray:
        """As the function of that name: candidates by a product, ties by differences."""
        b = c - self.mid
        bb = (b * b).sum(axis=1)
        d = (-2.0 * b) @ self.a
        d += bb[:, None]
        k = d.argmin(axis=0)
        if len(c) > 1:
            best = d[k, self.rows]
            d[k, self.rows] = np.inf
            for i in np.flatnonzero(d.min(axis=0) - best <= 1e-9 * (self.aa + (bb.max() + 1e-300))).tolist():
                k[i] = ((self.x[i] - c) ** 2).sum(axis=1).argmin()
        return k

    def sums(self, c: np.ndarray) -> Sums:
        k, wide, w = self.nearest(c), len(self.columns), len(self.seqs)
        off = self.xt - c.T[:, k]
        self.load[:, -1] = (off * off).sum(axis=0)
        cell = (self.at * len(c) + k) * wide
        all_ = np.bincount((cell[:, None] + self.columns).ravel(), self.load.ravel(), w * len(c) * wide).reshape(w, len(c), wide)
        return Sums(self.seqs, all_[:, :, 0], all_[:, :, 1:-2], all_[:, :, -2], all_[:, :, -1])


#: Points that two_nearest looks at in one go, so that their distances stay in the processor's cache.
STRIP = 2048


#: Coordinates from which points stand one after another in memory (they are picked one by one), not their coordinates.
WIDE = 17


def lengths(x: np.ndarray) -> np.ndarray:
    """Squared lengths of points that stand in columns."""
    return np.einsum("ij,ij->j", x, x)


def laid(x: np.ndarray) -> np.ndarray:
    """Points in rows as columns, in the memory order for their width."""
    return np.ascontiguousarray(x, dtype=float).T if x.shape[1] >= WIDE else np.ascontiguousarray(x.T, dtype=float)


def pick(x: np.ndarray, at: np.ndarray) -> np.ndarray:
    """x[:, at] in x's memory order."""
    return x.T.take(at, axis=0).T if x.shape[0] >= WIDE else x.take(at, axis=1)


def off_by(x: np.ndarray, c: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Squared distances of points in columns to row at[i] of c each."""
    return lengths(x - pick(c.T if len(c.T) >= WIDE else c.T.copy(), at))


def two_nearest(x: np.ndarray, c: np.ndarray, guess: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For points in columns: index of the nearest centroid (the lowest of equals), the squared distance to it and to the next one (inf if there is none).

    guess: a centroid for each point; the index is looked for where another one is nearer.
    """
    n, cc, twice = x.shape[1], (c * c).sum(axis=1)[:, None], -2.0 * c
    k, near, then = np.empty(n, dtype=np.int64), np.empty(n), np.empty(n)
    for lo in range(0, n, STRIP):
        part = x[:, lo : lo + STRIP]
        rows, xx, d = np.arange(part.shape[1]), lengths(part), twice @ part
        d += cc
        best = d.min(axis=0)
        if guess is None:
            at = d.argmin(axis=0)
        else:
            at = guess[lo : lo + STRIP].astype(np.int64)
            wrong = np.flatnonzero(best < d[at, rows])
            at[wrong] = d[:, wrong].argmin(axis=0)
        d[at, rows] = np.inf
        next_ = d.min(axis=0)
        close = np.flatnonzero(next_ - best <= 1e-9 * (xx + (cc.max() + 1e-300)))
        for i in range(0, len(close), 256):  # differences settle what rounding leaves open
            some = close[i : i + 256]
            at[some] = ((part[:, some].T[:, None, :] - c[None, :, :]) ** 2).sum(axis=2).argmin(axis=1)
        k[lo : lo + STRIP], near[lo : lo + STRIP], then[lo : lo + STRIP] = at, np.maximum(xx + best, 0.0), np.maximum(xx + next_, 0.0)
    return k, near, then


def add_up(cell: np.ndarray, x: np.ndarray, size: int, sign: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Number, sum and sum of squared lengths of the points in columns by cell; with signs, of signed points."""
    xx = lengths(x)
    if len(cell) < 256:
        one = np.zeros((size, len(cell)))
        one[cell, np.arange(len(cell))] = 1.0 if sign is None else sign
        return one.sum(axis=1), one @ x.T, one @ xx
    n, sxx = np.bincount(cell, sign, size).astype(float), np.bincount(cell, xx if sign is None else xx * sign, size)
    if len(x) < WIDE:
        return n, np.stack([np.bincount(cell, row if sign is None else row * sign, size) for row in x], axis=1), sxx
    order = np.argsort(cell.astype(np.int16 if size < 32_768 else np.int64), kind="stable")
    sx, held = np.zeros((size, len(x))), np.bincount(cell, minlength=size)
    some = np.flatnonzero(held)
    rows = x.T.take(order, axis=0)
    if sign is not None:
        rows *= sign[order][:, None]
    sx[some] = np.add.reduceat(rows, (np.cumsum(held) - held)[some], axis=0)
    return n, sx, sxx


class Bounds:
    """Which points can have changed their cluster since the centroids were where they were looked at.

    own + way of the own centroid and next - longest way of the others bound the two distances. Both ways only grow, so a point keeps
    next - own as of the start (its mark) and is due when its cluster's ways have come up to it: the others aren't written.
    """

    def __init__(self, c: np.ndarray) -> None:
        self.c, self.way, self.others = c.copy(), np.zeros(len(c)), np.zeros(len(c))

    def move(self, c: np.ndarray) -> bool:
        """Whether any centroid has moved."""
        way = np.sqrt(((c - self.c) ** 2).sum(axis=1))
        if not way.any():
            return False
        others = np.full(len(c), way.max())
        others[way.argmax()] = np.delete(way, way.argmax()).max() if len(c) > 1 else 0.0
        self.c, self.way, self.others = c.copy(), self.way + way, self.others + others
        return True

    def due(self, at: np.ndarray, mark: np.ndarray, slack: float) -> np.ndarray:
        return np.flatnonzero(mark <= (self.way + self.others + slack).take(at))

    def marks(self, at: np.ndarray, own: np.ndarray, then: np.ndarray) -> np.ndarray:
        """then: as kept, with the others' way so far."""
        return then - own + self.way.take(at)

    def look(self, x: np.ndarray, at: np.ndarray, then: np.ndarray, slack: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Cluster, mark and kept next distance of the points due: first by the exact distance to the own centroid, then to all."""
        own = np.sqrt(off_by(x, self.c, at))
        left = np.flatnonzero(own + slack >= then - self.others.take(at))
        mark = self.marks(at, own, then)
        if len(left):
            k, near, far = two_nearest(x if len(left) == len(at) else pick(x, left), self.c, at[left])
            at, then = at.copy(), then.copy()
            at[left], then[left] = k, np.sqrt(far) + self.others.take(k)
            mark[left] = self.marks(k, np.sqrt(near), then[left])
        return at, mark, then


class Followed:
    """A window whose batches stand one after another, over all its passes: a pass looks at the points that can have changed their
    cluster and corrects the sums by those that have. sums(c) equals sums_of(x, seq, c)."""

    def __init__(self, x: np.ndarray, seq: np.ndarray) -> None:
        self.seqs, first = np.unique(seq, return_index=True)
        self.batch = np.repeat(np.arange(len(first)), np.diff([*first.tolist(), len(x)]))
        self.mid = x.mean(axis=0)
        self.a = laid(x - self.mid)
        self.large = float(np.sqrt(lengths(self.a).max()))
        self.bounds: Bounds | None = None

    def _first(self, b: np.ndarray) -> None:
        self.bounds = Bounds(b)
        self.at, near, far = two_nearest(self.a, b)
        self.then = np.sqrt(far)
        self.mark = self.bounds.marks(self.at, np.sqrt(near), self.then)
        self.total = add_up(self.batch * len(b) + self.at, self.a, len(self.seqs) * len(b))

    def sums(self, c: np.ndarray) -> Sums:
        b = c - self.mid
        bb = (b * b).sum(axis=1)
        if self.bounds is None or len(self.bounds.c) != len(b):
            self._first(b)
        elif self.bounds.move(b):
            slack = 1e-7 * max(self.large, float(np.sqrt(bb.max())))
            due = self.bounds.due(self.at, self.mark, slack)
            if len(due) > len(self.at) // 2:
                self._first(b)
            elif len(due):
                was, x = self.at[due], pick(self.a, due)
                k, self.mark[due], self.then[due] = self.bounds.look(x, was, self.then[due], slack)
                moved = np.flatnonzero(k != was)
                if len(moved):
                    x, row = pick(x, moved), self.batch[due[moved]] * len(b)
                    cell, sign = np.concatenate([row + k[moved], row + was[moved]]), np.repeat([1.0, -1.0], len(moved))
                    for total, more in zip(self.total, add_up(cell, pick(x, np.tile(np.arange(len(moved)), 2)), len(self.total[0]), sign), strict=True):
                        total += more
                    self.at[due] = k
        w = len(self.seqs)
        n, sa, aa = (v.reshape(w, len(c), *v.shape[1:]) for v in self.total)
        n = np.rint(n)
        sse = aa - 2.0 * np.einsum("wkd,kd->wk", sa, b) + n * bb
        small = (n > 0) & (sse <= 1e-6 * (aa + n * bb))
        if small.any():  # rounding would show
            some = np.flatnonzero(small.ravel()[self.batch * len(b) + self.at])
            cell = self.batch[some] * len(b) + self.at[some]
            sse = np.where(small, np.bincount(cell, off_by(pick(self.a, some), b, self.at[some]), w * len(b)).reshape(w, len(b)), sse)
        sse[n == 0] = 0.0
        sxx = aa + 2.0 * (sa @ self.mid) + n * float(self.mid @ self.mid)
        return Sums(self.seqs, n, sa + n[:, :, None] * self.mid, sxx, sse)


def update(counts: np.ndarray, sums: np.ndarray, old: np.ndarray) -> np.ndarray:
    """Means of the clusters; an empty one keeps its centroid."""
    out = old.copy()
    some = counts > 0
    out[some] = sums[some] / counts[some][:, None]
    return out


def fading(seqs: np.ndarray, newest: int, rho: float) -> np.ndarray:
    """rho ** antiquity of each batch."""
    return np.power(float(rho), (newest - seqs).astype(float))
