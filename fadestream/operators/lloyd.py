"""Weighted Lloyd over a window, for any way of making a pass over it.

A pass returns sums per (batch, cluster); the driver keeps K x d numbers and W x K rows whatever the window's size. Several
models share a pass. The fixed point is reached when the centroids repeat, or when the counts repeat and the error stands
still (sums of another order may differ in the last bits); it takes a confirming pass, which counts, also from a start that
is one.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field
from functools import cached_property
from typing import Protocol

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadestream.functions.kernels import Followed, Packed, Sums, nearest, sums_of, update
from fadestream.operators.distance import assign, cluster_stats, few_parts, gather, partial_stats


class Window(Protocol):
    """Something that can be passed over."""

    def passes(self, models: Sequence[np.ndarray]) -> list[Sums]: ...


@dataclass
class LocalWindow:
    """Points in memory: small windows, keyed state, experiment cells."""

    x: np.ndarray
    seq: np.ndarray
    weight: np.ndarray | None = None
    narrow: bool = True  # few coordinates are packed while the window is small, not followed

    @cached_property
    def packed(self) -> Packed | Followed:
        return (Packed if self._small and len(self.x) <= Packed.ROWS else Followed)(self.x, self.seq)

    @property
    def _small(self) -> bool:
        return self.narrow and self.x.shape[1] <= Packed.WIDTH

    @cached_property
    def packs(self) -> bool:
        """Whether passes share what they know of the points. Large windows are followed if they are narrow."""
        if self.weight is not None or not len(self.x):
            return False
        large = len(self.x) > Packed.ROWS
        return self._small and not large or (self._small or not large) and bool((np.diff(self.seq) >= 0).all())

    def passes(self, models: Sequence[np.ndarray]) -> list[Sums]:
        if self.packs:
            return [self.packed.sums(np.asarray(m, dtype=float)) for m in models]
        return [sums_of(self.x, self.seq, np.asarray(m, dtype=float), self.weight) for m in models]


class GrowingWindow:
    """All points so far, of batches that all weigh the same (rho = 1), held for exact passes that look at few of them.

    A point's centroid can't change before the centroids have moved by half the gap between its two nearest ones (each by at most the
    longest move of a pass). So every point has a mark on the way covered, and a pass looks only at points whose mark is reached; sums
    are corrected by the points that moved. They are exact for whole-number points. Sums come as one row for old batches (numbered -1)
    and one for each batch of the last `recent`.
    """

    #: Points of a new list of those whose marks come next; how many times more the list that it is made from holds.
    AHEAD, WIDER = 8192, 4

    def __init__(self, k: int, recent: int = 10) -> None:
        self.k, self.recent, self.n = k, recent, 0
        self.seqs: list[int] = [-1]
        self.starts: list[int] = []  # first point of each recent batch
        self.c: np.ndarray | None = None
        self.way, self.large = 0.0, 1.0
        self.lists: dict[int, tuple[float, np.ndarray, int]] = {}  # by level: all points up to a mark, when there were so many

    def add(self, seq: int, x: np.ndarray) -> None:
        d = x.shape[1]
        if not self.n:
            self.x, self.at, self.mark = np.empty((0, d)), np.empty(0, dtype=np.int16), np.empty(0)
            self.sums = Sums.zeros(self.seqs, self.k, d)
        if self.n + len(x) > len(self.x):
            room = max(1024, (self.n + len(x)) * 3 // 2)
            for name in ("x", "at", "mark"):
                old = getattr(self, name)
                new = np.empty((room, *old.shape[1:]), dtype=old.dtype)
                new[: self.n] = old[: self.n]
                setattr(self, name, new)
        new = np.arange(self.n, self.n + len(x))
        self.x[new], self.at[new], self.mark[new] = x, -1, -np.inf
        self.large = max(self.large, float(np.abs(x).max()))
        self.seqs.append(seq)
        self.starts.append(self.n)
        self.n += len(x)
        s = self.sums
        rows = [np.concatenate([v, np.zeros((1, *v.shape[1:]))]) for v in (s.n, s.sx, s.sxx, s.sse)]
        while len(self.seqs) > 1 and self.seqs[1] <= seq - self.recent:  # the oldest recent batch joins the old ones
            for v in rows:
                v[0] += v[1]
            rows = [np.delete(v, 1, axis=0) for v in rows]
            del self.seqs[1], self.starts[0]
        self.sums = Sums(np.array(self.seqs), *rows)

    def _ahead(self, level: int = 0) -> tuple[float, np.ndarray]:
        """A mark not behind the way covered, and points among which are all up to it: about AHEAD at level 0, WIDER times more a level."""
        size = self.AHEAD * self.WIDER**level
        if size >= self.n:
            return np.inf, np.arange(self.n)
        if level not in self.lists or self.way > self.lists[level][0] or self.n - self.lists[level][2] > 2 * size:
            horizon, at = self._ahead(level + 1)
            marks = self.mark[at]
            cut = max(self.way, float(np.partition(marks, size)[size])) if len(at) > size else np.inf
            if cut < horizon:
                horizon, at = cut, at[marks <= cut]
            self.lists[level] = horizon, at, self.n
        horizon, at, n = self.lists[level]
        return horizon, np.concatenate([at, np.arange(n, self.n)])  # those that came later may be due as well

    def _look(self, c: np.ndarray) -> None:
        """Bring the points whose marks are reached to their nearest centroids."""
        if self.c is not None:
            self.way += float(np.sqrt(((c - self.c) ** 2).sum(axis=1).max()))
        self.c = c.copy()
        near = self._ahead()[1]
        due = near[self.mark[near] <= self.way]
        if not len(due):
            return
        x, was = self.x[due], self.at[due]
        off = np.ascontiguousarray(x.T) - c[:, :, None]
        off *= off
        d2 = off.sum(axis=1)
        k, own, then = np.zeros(len(due), dtype=np.int64), d2[0], np.full(len(due), np.inf)
        for j in range(1, len(c)):  # the lowest of equals
            then = np.minimum(then, np.maximum(own, d2[j]))
            k[d2[j] < own] = j
            own = np.minimum(own, d2[j])
        self.mark[due] = self.way + (np.sqrt(then) - np.sqrt(own)) / 2.0 - 1e-9 * self.large
        moved = np.flatnonzero(k != was)
        if len(moved):
            x, k, was, row = x[moved], k[moved], was[moved].astype(np.int64), np.searchsorted(self.starts, due[moved], "right")
            self.at[due[moved]] = k
            xx, old, s = (x * x).sum(axis=1), was >= 0, self.sums
            for target, value in ((s.n, np.ones(len(x))), (s.sx, x), (s.sxx, xx)):
                np.add.at(target, (row, k), value)
                np.subtract.at(target, (row[old], was[old]), value[old])

    def passes(self, models: Sequence[np.ndarray]) -> list[Sums]:
        out = []
        for m in models:
            c = np.asarray(m, dtype=float)
            self._look(c)
            s = self.sums
            sse = np.maximum(s.sxx - 2.0 * np.einsum("wkd,kd->wk", s.sx, c) + s.n * (c * c).sum(axis=1), 0.0)
            out.append(Sums(s.seqs, s.n.copy(), s.sx.copy(), s.sxx.copy(), sse))
        return out


@dataclass
class SparkWindow:
    """A points relation (batch_seq, x); one distributed scan a pass, whatever the number of models."""

    df: DataFrame
    weight_col: str | None = None
    direct: bool | None = None

    def passes(self, models: Sequence[np.ndarray]) -> list[Sums]:
        """Few tasks send their sums straight here (one stage); many add them up on executors first (one exchange of sums)."""
        d, k = np.asarray(models[0]).shape[1], [len(m) for m in models]
        if self.direct is None:
            self.direct = few_parts(self.df, 16 * sum(k))
        stats = partial_stats(self.df, models, self.weight_col) if self.direct else cluster_stats(self.df, models, self.weight_col)
        return gather(stats, len(models), k, d)


#: Points up to which a window is pulled into memory instead of being scanned by a job a pass.
LOCAL_ROWS = 20_000


def window_of(df: DataFrame, local_rows: int = LOCAL_ROWS) -> Window:
    """The window over a points relation: in memory if it is small (one job finds out and fetches it), else distributed."""
    cols = ["batch_seq", "x"] if "batch_seq" in df.columns else ["x"]
    rows = df.select(*cols).limit(local_rows + 1).toArrow()
    if rows.num_rows > local_rows or not rows.num_rows:
        return SparkWindow(df if "batch_seq" in df.columns else df.withColumn("batch_seq", F.lit(0).cast("long")))
    x = np.asarray(rows.column(len(cols) - 1).combine_chunks().flatten(), dtype=float).reshape(rows.num_rows, -1)
    seq = rows.column(0).to_numpy() if len(cols) == 2 else np.zeros(len(x), dtype=np.int64)
    return LocalWindow(x, seq)


@dataclass
class LloydResult:
    centroids: np.ndarray
    sums: Sums
    iterations: int
    distances: int
    converged: bool
    errors: list[float] = field(default_factory=list)


Weights = Callable[[np.ndarray], np.ndarray]


def even(seqs: np.ndarray) -> np.ndarray:
    return np.ones(len(seqs))


def lloyd_many(window: Window, starts: Sequence[np.ndarray], weights: Sequence[Weights] | Weights = even, *, max_iter: int = 100, tol: float = 0.0) -> list[LloydResult]:
    """Lloyd from each start over the same window; settled models leave the passes. errors[0] is the error of the start."""
    per = list(weights) if isinstance(weights, Sequence) else [weights] * len(starts)
    now = [np.asarray(s, dtype=float).copy() for s in starts]
    errors: list[list[float]] = [[] for _ in starts]
    last: list[Sums | None] = [None] * len(starts)
    used, spent, done = [0] * len(starts), [0] * len(starts), [False] * len(starts)
    for _ in range(max_iter):
        live = [i for i, x in enumerate(done) if not x]
        if not live:
            break
        for i, s in zip(live, window.passes([now[i] for i in live]), strict=True):
            w = per[i](s.seqs)
            used[i] += 1
            spent[i] += s.points * len(now[i])
            errors[i].append(s.error(w))
            moved = update(*s.weighted(w), now[i])
            prev = last[i]
            still = prev is not None and prev.n.shape == s.n.shape and (prev.n == s.n).all() and abs(errors[i][-1] - errors[i][-2]) <= 1e-12 * max(errors[i][-1], 1e-300)
            shift = float(((moved - now[i]) ** 2).sum())
            if prev is not None and (np.array_equal(moved, now[i]) or still) or (tol and shift <= tol * tol * max(float((now[i] ** 2).sum()), 1e-300)):
                done[i] = True
            else:
                now[i] = moved
            last[i] = s
    out = []
    for i in range(len(starts)):
        if not done[i]:  # the sums must be those of the centroids that are returned
            last[i] = window.passes([now[i]])[0]
            spent[i] += last[i].points * len(now[i])
            errors[i].append(last[i].error(per[i](last[i].seqs)))
        out.append(LloydResult(now[i], last[i], used[i] + (not done[i]), spent[i], done[i], errors[i]))
    return out


def lloyd(window: Window, start: np.ndarray, weights: Weights = even, *, max_iter: int = 100, tol: float = 0.0) -> LloydResult:
    return lloyd_many(window, [start], weights, max_iter=max_iter, tol=tol)[0]


def steps(window: Window, start: np.ndarray, n: int, weights: Weights = even) -> np.ndarray:
    """Exactly n updates, converged or not."""
    c = np.asarray(start, dtype=float)
    for _ in range(n):
        s = window.passes([c])[0]
        c = update(*s.weighted(weights(s.seqs)), c)
    return c


def reassigned_counts(window: Window, model: np.ndarray, start: np.ndarray, home: np.ndarray) -> dict[int, int]:
    """By batch, how many points of cluster k of `model` are nearest to another start centroid than home[k]. One scan."""
    if isinstance(window, LocalWindow):
        off = home[nearest(window.x, model)[0]] != nearest(window.x, start)[0]
        seqs, n = np.unique(window.seq[off], return_counts=True)
        return dict(zip(seqs.tolist(), n.tolist(), strict=True))
    both = assign(assign(window.df.select("batch_seq", "x"), model).select("batch_seq", "x", F.col("k").alias("was")), start)
    at = F.array(*(F.lit(int(h)) for h in home))
    rows = both.where(F.get(at, F.col("was")) != F.col("k")).groupBy("batch_seq").agg(F.count(F.lit(1)).alias("n")).collect()
    return {r["batch_seq"]: r["n"] for r in rows}


def lloyd_points(x: np.ndarray, w: np.ndarray, start: np.ndarray, max_iter: int = 100) -> LloydResult:
    """Lloyd over a handful of weighted points."""
    return lloyd(LocalWindow(x, np.zeros(len(x), dtype=np.int64), w), start, max_iter=max_iter)
