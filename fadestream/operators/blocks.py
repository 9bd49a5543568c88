"""A block of points of any size for one task: in memory while small, else in a temporary file of the task, and passed over in chunks.

Every kernel holds one chunk; Lloyd's passes look only at the points whose centroid can have changed.
"""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterator, Sequence

import numpy as np

from fadestream.functions.kernels import STRIP, WIDE, Bounds, Sums, add_up, laid, lengths, pick, two_nearest
from fadestream.operators.seeding import fill


class PointBlock:
    """Points of one width, added in arrays, with the state that the passes keep for each of them. In a chunk they stand in columns.

    A Window of Lloyd's iteration: a pass looks at the points whose Bounds meet; sums are corrected by the points that change their
    cluster.
    """

    #: Points of a chunk; bytes of all chunks with their state up to which a block stays in memory.
    ROWS, HELD = 16_384, 256_000_000
    #: State of a point beside its coordinates: cluster, its mark and next distance as Bounds has them, squared distance to the seeds.
    STATE = (("at", np.int32), ("mark", np.float64), ("then", np.float64), ("far", np.float64))

    def __init__(self, held: int | None = None) -> None:
        self.held = self.HELD if held is None else held
        self.n, self.d, self.file = 0, 0, None
        self.chunks: list[dict[str, np.ndarray]] = []
        self.sizes: list[int] = []
        self.rest: list[np.ndarray] = []
        self.bounds: Bounds | None = None
        self.large = 1.0

    def __len__(self) -> int:
        return self.n

    @property
    def shape(self) -> tuple[int, int]:
        return self.n, self.d

    def add(self, x: np.ndarray) -> None:
        if not np.isfinite(x).all():
            raise ValueError("points must be finite")
        self.d = x.shape[1]
        self.rest.append(x)
        if sum(map(len, self.rest)) >= self.ROWS:
            x = np.concatenate(self.rest)
            whole = len(x) // self.ROWS * self.ROWS
            for i in range(0, whole, self.ROWS):
                self._append(x[i : i + self.ROWS])
            self.rest = [x[whole:].copy()]

    def done(self) -> PointBlock:
        """No more points come."""
        x, self.rest = (np.concatenate(self.rest) if self.rest else np.empty((0, 0))), []
        if len(x):
            self._append(x)
        return self

    def _append(self, x: np.ndarray) -> None:
        self.sizes.append(len(x))
        self.n += len(x)
        self.width = 8 * self.d + sum(np.dtype(t).itemsize for _, t in self.STATE)
        if self.file is None and len(self.sizes) * self.ROWS * self.width > self.held:
            self.file = tempfile.TemporaryFile(buffering=0)  # gone when the block is
            chunks, self.chunks = self.chunks, []
            for i, old in enumerate(chunks):
                self.store(i, "x", old["x"])
        if self.file is None:
            self.chunks.append({"x": laid(np.array(x, dtype=float))})
        else:
            self.store(len(self.sizes) - 1, "x", laid(x))

    def _place(self, i: int, name: str) -> tuple[int, type]:
        at = i * self.ROWS * self.width
        if name == "x":
            return at, np.float64
        at += self.ROWS * self.d * 8
        for other, kind in self.STATE:
            if other == name:
                return at, kind
            at += self.ROWS * np.dtype(kind).itemsize
        raise KeyError(name)

    def load(self, i: int, name: str) -> np.ndarray:
        if self.file is None:
            return self.chunks[i][name]
        at, kind = self._place(i, name)
        shape = (self.sizes[i],) if name != "x" else (self.sizes[i], self.d) if self.d >= WIDE else (self.d, self.sizes[i])
        out, got = np.empty(shape, dtype=kind), 0
        view = memoryview(out).cast("B")
        while got < len(view):
            n = os.preadv(self.file.fileno(), [view[got:]], at + got)
            if n <= 0:
                raise OSError("the block's file ends early")
            got += n
        return out.T if name == "x" and self.d >= WIDE else out

    def store(self, i: int, name: str, value: np.ndarray) -> None:
        if self.file is None:
            self.chunks[i][name] = value
            return
        at, kind = self._place(i, name)
        view, put = memoryview(np.ascontiguousarray(value.T if name == "x" and self.d >= WIDE else value, dtype=kind)).cast("B"), 0
        while put < len(view):
            put += os.pwrite(self.file.fileno(), view[put:], at + put)

    def each(self) -> Iterator[tuple[int, np.ndarray]]:
        for i in range(len(self.sizes)):
            yield i, self.load(i, "x")

    def rows(self, at: np.ndarray) -> np.ndarray:
        """The points at these places, in their order."""
        out, chunk = np.empty((len(at), self.d)), at // self.ROWS
        for i in np.unique(chunk).tolist():
            here = np.flatnonzero(chunk == i)
            out[here] = pick(self.load(i, "x"), at[here] - i * self.ROWS).T
        return out

    def kmpp(self, k: int, rng: np.random.Generator) -> np.ndarray:
        """As local_kmpp, with the same draws."""
        chosen: list[np.ndarray] = []
        for r in range(k):
            least, pick = np.inf, None
            for i, x in self.each():
                if r:
                    far = lengths(x - chosen[-1][:, None])
                    far = far if r == 1 else np.minimum(self.load(i, "far"), far)
                    self.store(i, "far", far)
                    some = np.flatnonzero(far > 0)
                    key = rng.exponential(size=len(some)) / far[some]
                else:
                    some, key = np.arange(x.shape[1]), rng.exponential(size=x.shape[1])
                if len(key) and (j := int(key.argmin())) >= 0 and key[j] < least:
                    least, pick = key[j], x[:, some[j]].copy()
            if pick is None:
                break
            chosen.append(pick)
        return fill(np.array(chosen), k)

    def _first(self, c: np.ndarray) -> None:
        self.total, self.large, self.bounds = Sums.zeros([0], *c.shape), 1.0, Bounds(c)
        for i, x in self.each():
            at, near, far = two_nearest(x, c)
            self._shift(add_up(at, x, len(c)))
            self.large = max(self.large, float(np.sqrt(lengths(x).max())))
            then = np.sqrt(far)
            for name, v in (("at", at.astype(np.int32)), ("mark", self.bounds.marks(at, np.sqrt(near), then)), ("then", then)):
                self.store(i, name, v)

    def _shift(self, more: tuple[np.ndarray, np.ndarray, np.ndarray]) -> None:
        for v, m in zip((self.total.n, self.total.sx, self.total.sxx), more, strict=True):
            v[0] += m

    def _look(self, c: np.ndarray) -> None:
        if self.bounds is None or self.bounds.c.shape != c.shape:
            self._first(c)
            return
        if not self.bounds.move(c):
            return
        slack = 1e-7 * max(self.large, float(np.sqrt((c * c).sum(axis=1).max())))
        for i in range(len(self.sizes)):
            at, mark = self.load(i, "at"), self.load(i, "mark")
            due = self.bounds.due(at, mark, slack)
            if not len(due):
                continue
            x, then, was = self.load(i, "x"), self.load(i, "then"), at[due]
            x = x if len(due) == len(at) else pick(x, due)
            k, mark[due], then[due] = self.bounds.look(x, was, then[due], slack)
            self.store(i, "mark", mark)
            self.store(i, "then", then)
            moved = np.flatnonzero(k != was)
            if len(moved):
                self._shift(add_up(np.concatenate([k[moved], was[moved]]), pick(x, np.tile(moved, 2)), len(c), np.repeat([1.0, -1.0], len(moved))))
                at[due] = k
                self.store(i, "at", at)

    def passes(self, models: Sequence[np.ndarray]) -> list[Sums]:
        out = []
        for m in models:
            c = np.asarray(m, dtype=float)
            self._look(c)
            s = self.total
            sse = np.maximum(s.sxx - 2.0 * np.einsum("wkd,kd->wk", s.sx, c) + s.n * (c * c).sum(axis=1), 0.0)
            out.append(Sums(s.seqs, s.n.copy(), s.sx.copy(), s.sxx.copy(), sse))
        return out

    def errors(self, xi: np.ndarray, alphas: Sequence[float]) -> list[float]:
        """Mean error under the centroids of the last pass if every cluster is moved along its row of xi, for each length.

        |y - c|^2 = |y|^2 + |c|^2 - 2 c.x - 2 a c.xi for y = x + a xi: the first adds up from the sums of the clusters, of the rest the
        least is looked for, cluster by cluster.
        """
        c, s = self.bounds.c, self.total
        cc, twice, cross = (c * c).sum(axis=1), -2.0 * c, 2.0 * (xi @ c.T)
        a = np.asarray(alphas, dtype=float)
        sums = s.sxx[0].sum() + 2.0 * a * (xi * s.sx[0]).sum() + a * a * (s.n[0] @ (xi * xi).sum(axis=1))
        for i, x in self.each():
            at = self.load(i, "at")
            order = np.argsort(at.astype(np.int16 if len(c) < 32_768 else np.int64), kind="stable")
            ends = np.cumsum(np.bincount(at, minlength=len(c)))
            for k in range(len(c)):
                for lo in range(ends[k - 1] if k else 0, ends[k], STRIP):
                    g = twice @ pick(x, order[lo : min(lo + STRIP, ends[k])])
                    for j in range(len(a)):
                        sums[j] += (g + (cc - a[j] * cross[k])[:, None]).min(axis=0).sum()
        return list(np.maximum(sums, 0.0) / self.n)

    def move(self, step: np.ndarray) -> None:
        """Every point goes along the row of its cluster."""
        way = laid(step)
        for i, x in self.each():
            self.store(i, "x", x + pick(way, self.load(i, "at")))
        self.bounds = None
