"""The two clusterers: one that fades old batches, and the reference that is told when the distribution changed.

Small windows are held in memory and stepped by the array kernels; larger ones live in a WindowStore and every pass is one
distributed scan. Both go through the same code above the pass.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadestream.functions.kernels import Sums, fading, nearest
from fadestream.functions.theory import choose_t_max
from fadestream.operators.errors import within_scatter
from fadestream.operators.lloyd import GrowingWindow, LloydResult, LocalWindow, SparkWindow, Window, even, lloyd, reassigned_counts
from fadestream.operators.matching import seed_bound
from fadestream.operators.seeding import HELD_SEEDINGS, SEEDINGS, HeldPoints, local_kmpp
from fadestream.operators.starts import POLICIES, Centres, fresh_centres, past_centres
from fadestream.sources.window_store import WindowStore


@dataclass
class StepResult:
    seq: int
    method: str
    centroids: np.ndarray
    sums: Sums
    start: np.ndarray
    init_faded: float
    final_faded: float
    iterations: int
    converged: bool
    distances: dict[str, int]
    mass: float
    wall_ms: float
    past: Centres | None = None
    fresh: Centres | None = None
    detail: dict = field(default_factory=dict)

    def since_drift(self, drift_seq: int) -> float:
        """Mean squared distance over the batches from drift_seq on, from the sums of the last pass."""
        return self.sums.keep(self.sums.seqs >= drift_seq).error(np.ones(int((self.sums.seqs >= drift_seq).sum())))

    @property
    def total_distances(self) -> int:
        return sum(self.distances.values())


class _Base:
    """Batches in, window out."""

    name = ""

    def __init__(self, k: int, *, seed: int = 0, max_iter: int = 100, tol: float = 0.0, local_rows: int = 200_000, store: WindowStore | None = None, seeding: str = "kmpp", model_id: str | None = None, grown: GrowingWindow | None = None, windows: dict | None = None) -> None:
        self.k, self.seed, self.max_iter, self.tol, self.local_rows, self.store, self.seeding = k, seed, max_iter, tol, local_rows, store, seeding
        self.model_id = model_id or self.name
        self.grown = grown  # instead of held: for batches that never leave and all weigh the same
        self.windows = windows  # of clusterers that step over the same arrays in turn: the last window of any of them
        self.held: list[tuple[int, np.ndarray]] = []
        self.ids: list | None = None
        self.stored: list[int] = []
        self.seq = -1
        self.centroids: np.ndarray | None = None
        self.sums: Sums | None = None

    def _take(self, batch: DataFrame | np.ndarray, seq: int | None) -> tuple[Window | None, int]:
        """Append a batch; the window over it alone (None if it is empty), and its size."""
        self.seq = self.seq + 1 if seq is None else seq
        self.ids = None
        if isinstance(batch, np.ndarray):
            x = batch
        else:
            if self.store is not None:
                self.store.append(batch, self.seq)
                self.stored.append(self.seq)
                one = self.store.window(self.seq, self.seq)
                odd = F.col("x").isNull() | F.exists("x", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
                n, bad = one.agg(F.count(F.lit(1)), F.count_if(odd)).first()
                if bad:
                    self.stored.remove(self.seq)
                    self.store.drop(self.seq)
                    raise ValueError("points must be finite")
                return (SparkWindow(one) if n else None), n
            rows = batch.select("x", *(["point_id"] if "point_id" in batch.columns else [])).limit(self.local_rows + 1).toArrow()
            self.ids = rows.column(1).to_pylist() if rows.num_columns > 1 else None
            if rows.num_rows > self.local_rows:
                raise ValueError(f"a batch of over {self.local_rows} rows needs a WindowStore")
            x = np.asarray(rows.column(0).combine_chunks().flatten(), dtype=float).reshape(rows.num_rows, -1)
        if not len(x):
            return None, 0
        if not np.isfinite(x).all():
            raise ValueError("points must be finite")
        if self.grown is not None:
            self.grown.add(self.seq, x)
        else:
            self.held.append((self.seq, x))
        return LocalWindow(x, np.full(len(x), self.seq)), len(x)

    def _window(self) -> Window:
        if self.store is not None:
            df = self.store.window(min(self.stored), max(self.stored))
            return SparkWindow(df)
        if self.grown is not None:
            return self.grown
        key = tuple((s, id(x)) for s, x in self.held)
        if self.windows is not None and key in self.windows:
            return self.windows[key]
        window = LocalWindow(np.concatenate([x for _, x in self.held]), np.concatenate([np.full(len(x), s) for s, x in self.held]), narrow=self.windows is None)
        if self.windows is not None:
            self.windows.clear()
            self.windows[key] = window
        return window

    def _evict(self, keep_from: int) -> None:
        self.held = [(s, x) for s, x in self.held if s >= keep_from]
        if self.store is not None:
            self.stored = [s for s in self.stored if s >= keep_from]
            self.store.drop_before(keep_from)

    def _seeds(self, newest: Window) -> np.ndarray:
        """Seeds of a batch, the same whether it is in memory or stored. Points without ids are numbered as they come."""
        seed = self.seed * 100_003 + self.seq
        if isinstance(newest, LocalWindow):
            ids = list(range(len(newest.x))) if self.ids is None or None in self.ids else self.ids
            return HELD_SEEDINGS[self.seeding](HeldPoints(newest.x, ids, seed), self.k)
        return SEEDINGS[self.seeding](newest.df, self.k, seed=seed)

    def _commit(self, r: LloydResult) -> None:
        self.centroids, self.sums = r.centroids, r.sums
        if self.store is not None:
            self.store.write_stats(self.model_id, self.seq, r.sums)
            self.store.write_model(self.model_id, self.seq, "final", r.centroids, r.sums.n.sum(axis=0))


class FadingClusterer(_Base):
    """Weight rho^age for each batch, T_max batches at most, a start policy, weighted Lloyd.

    t_max None: the smallest window whose next batch weighs at most tail_tol (endless for rho = 1). A first batch starts from
    its own seeds; an empty one ages the window and changes nothing else. track_bound: each step's detail gets the seed bound of
    its start, the constant that the bound leaves out, and the share of the window's mass that the start assigns to another
    cluster than the two clusterings it was made of (two passes more; for bounds that hold, c0_refine is mean or lloyd and
    recenter_past is true).
    """

    def __init__(self, k: int, rho: float, t_max: int | None = None, start: str | object = "pair", *, c0_refine: str = "none", recenter_past: bool = False, tail_tol: float = 1e-4, track_bound: bool = False, **options) -> None:  # noqa: ANN003
        self.policy = POLICIES[start]() if isinstance(start, str) else start
        self.name = self.policy.name
        super().__init__(k, **options)
        self.rho, self.c0_refine, self.recenter_past, self.track_bound = rho, c0_refine, recenter_past, track_bound
        self.t_max = t_max if t_max is not None else (choose_t_max(rho, tail_tol) if rho < 1 else None)
        if self.grown is not None and (rho != 1 or self.t_max is not None or self.store is not None):
            raise ValueError("a growing window needs rho = 1, no t_max and no store")

    def _weights(self, seqs: np.ndarray) -> np.ndarray:
        return fading(seqs, self.seq, self.rho)

    def step(self, batch: DataFrame | np.ndarray, seq: int | None = None, shared: tuple[np.ndarray, Sums, np.ndarray] | None = None, seeds: np.ndarray | None = None) -> StepResult | None:
        """shared: (previous centroids, their sums, seeds of the new batch) when several policies are compared on equal terms; seeds: those
        of the new batch where they are drawn already."""
        began = time.perf_counter()
        newest, n_new = self._take(batch, seq)
        if self.t_max is not None:
            self._evict(self.seq - self.t_max + 1)
        if newest is None:
            return None
        rng = np.random.default_rng([self.seed, 7, self.seq + 1])
        before_c, before_s = (shared[0], shared[1]) if shared else (self.centroids, self.sums)
        window = self._window()
        past = fresh = None
        spent: dict[str, int] = {}
        if before_c is None:
            start_c, detail = self._seeds(newest) if seeds is None else seeds, {}
            spent["seeding"] = n_new * self.k
        else:
            past = past_centres(before_c, before_s, self.seq, self.rho, self.t_max, self.recenter_past)
            if self.policy.name != "carry":
                seeds = shared[2] if shared else self._seeds(newest) if seeds is None else seeds
                fresh, more = fresh_centres(newest, seeds, self.c0_refine)
                spent["seeding"] = n_new * self.k + more
            mass = float(past.w.sum() + n_new)
            s = self.policy.start(past, fresh, mass, rng)
            start_c, detail = s.c, dict(s.detail)
            if self.track_bound and fresh is not None:
                detail |= self._bound(window, before_c, seeds, past, fresh, start_c, mass)
            if s.distances:
                spent["pairing" if self.policy.name == "pair" else "inner"] = s.distances
        r = lloyd(window, start_c, self._weights, max_iter=self.max_iter, tol=self.tol)
        spent["lloyd"] = r.distances
        self._commit(r)
        mass = float((self._weights(r.sums.seqs)[:, None] * r.sums.n).sum())
        return StepResult(self.seq, self.name, r.centroids, r.sums, start_c, r.errors[0], r.errors[-1], r.iterations, r.converged, spent, mass, (time.perf_counter() - began) * 1e3, past, fresh, detail)

    def _bound(self, window: Window, before: np.ndarray, seeds: np.ndarray, past: Centres, fresh: Centres, start: np.ndarray, mass: float) -> dict:
        """Bound, constant and reassigned share of a start. Older points belong to the previous centroids, new ones to the seeds (of which c0_refine took the means)."""
        taken = fresh.c if self.c0_refine == "lloyd" else seeds
        parts = window.passes([before, taken])
        old, new = parts[0].keep(parts[0].seqs < self.seq), parts[1].keep(parts[1].seqs == self.seq)
        const = bound_const(old, new, self.rho, self.seq, mass)
        both, w = np.concatenate([past.c, fresh.c]), np.concatenate([past.w, fresh.w])
        home, _ = nearest(both, start)  # the cluster of the start that answers for each of the two sets' clusters
        return {"seed_bound": seed_bound(past.c, past.w, fresh.c, fresh.w, start, mass), "const": const, "reassigned": self._reassigned(window, before, taken, start, home, float(w.sum()))}

    def _reassigned(self, window: Window, before: np.ndarray, taken: np.ndarray, start: np.ndarray, home: np.ndarray, mass: float) -> float:
        """Share of the mass whose nearest start centroid isn't the one that its old cluster goes to."""
        moved = 0.0
        for seqs, model, at in ((None, before, home[: self.k]), (self.seq, taken, home[self.k :])):
            for seq, n in reassigned_counts(window, model, start, at).items():
                if (seq == self.seq) == (seqs is not None):
                    moved += float(self.rho ** (self.seq - seq)) * n
        return moved / mass

    def resume(self) -> int | None:
        """Load the last committed model and the retained window from the store; the batch number reached."""
        done = self.store.last_model(self.model_id)
        if done is None:
            return None
        rows = self.store.centroids(self.model_id).where(F.col("batch_seq") == done).orderBy("k").collect()
        self.centroids = np.array([r["c"] for r in rows])
        stats = self.store.stats(self.model_id).where(F.col("batch_seq") == done).collect()
        seqs = sorted({r["seq"] for r in stats})
        s = Sums.zeros(seqs, self.k, self.centroids.shape[1])
        for r in stats:
            i = seqs.index(r["seq"])
            s.n[i, r["k"]], s.sx[i, r["k"]], s.sxx[i, r["k"]], s.sse[i, r["k"]] = r["n"], r["sx"], r["sxx"], r["sse"]
        self.sums, self.seq = s, done
        self.stored = [b for b in self.store.batches() if b <= done and (self.t_max is None or b > done - self.t_max)]
        return done


class DriftOracleClusterer(_Base):
    """The reference: on a signalled change all history goes and the new batch is seeded; then plain Lloyd over what is left.

    max_batches caps the window between changes (none by default).
    """

    name = "reference"

    def __init__(self, k: int, *, max_batches: int | None = None, **options) -> None:  # noqa: ANN003
        super().__init__(k, **options)
        self.max_batches, self.drift_seq = max_batches, 0

    def step(self, batch: DataFrame | np.ndarray, is_drift: bool, seq: int | None = None, seeds: np.ndarray | None = None) -> StepResult | None:
        began = time.perf_counter()
        newest, n_new = self._take(batch, seq)
        spent: dict[str, int] = {}
        if is_drift or self.centroids is None:
            self._evict(self.seq)
            self.drift_seq = self.seq
            self.centroids = None
        if self.max_batches:
            self._evict(self.seq - self.max_batches + 1)
        if newest is None:
            return None
        if self.centroids is None:
            start_c = seeds if seeds is not None else self._seeds(newest)
            spent["seeding"] = n_new * self.k
        else:
            start_c = self.centroids
        r = lloyd(self._window(), start_c, even, max_iter=self.max_iter, tol=self.tol)
        spent["lloyd"] = r.distances
        self._commit(r)
        return StepResult(self.seq, self.name, r.centroids, r.sums, start_c, r.errors[0], r.errors[-1], r.iterations, r.converged, spent, float(r.sums.n.sum()), (time.perf_counter() - began) * 1e3)


def clusterer(mode: str, k: int, **options) -> FadingClusterer | DriftOracleClusterer:  # noqa: ANN003
    """mode fading: passive forgetting; reset: active forgetting on a signal; static: no forgetting; newest: the last batch only."""
    if mode == "reset":
        return DriftOracleClusterer(k, **options)
    if mode == "static":
        return FadingClusterer(k, 1.0, None, **({"start": "carry"} | options))
    if mode == "newest":
        return FadingClusterer(k, options.pop("rho", 1.0), 1, **options)
    if mode == "fading":
        return FadingClusterer(k, **options)
    raise ValueError(f"unknown mode {mode}")


def corrupt_signal(flags: list[bool], p_false: float, p_miss: float, seed: int = 0) -> list[bool]:
    """A detector's signal: false alarms with p_false, missed changes with p_miss."""
    rng = np.random.default_rng(seed)
    u = rng.random(len(flags))
    return [bool(x >= p_miss) if f else bool(x < p_false) for f, x in zip(flags, u, strict=True)]


def bound_slack(step: StepResult) -> float | None:
    """How far the bound plus its constant lies above the start's faded error; None for steps that didn't track it (first ones, carry-over)."""
    if "const" not in step.detail:
        return None
    return step.detail["seed_bound"] + step.detail["const"] - step.init_faded


def bound_const(past_sums: Sums, fresh_sums: Sums, rho: float, newest: int, mass: float) -> float:
    """What the bound leaves out: scatter of the points about the weighted means of both clusterings, by the window's mass."""
    w = fading(past_sums.seqs, newest, rho)
    return (within_scatter(past_sums, w) + within_scatter(fresh_sums, np.ones(len(fresh_sums.seqs)))) / mass


class DecayedKMeans:
    """The library-style comparator: each batch is assigned once, centroids are running means whose old weight decays; no window is kept."""

    name = "decayed"

    def __init__(self, k: int, decay: float = 0.5, start: np.ndarray | None = None, seed: int = 0) -> None:
        self.k, self.decay, self.centroids, self.seed = k, decay, start, seed
        self.weights = np.zeros(k)

    def step(self, batch: DataFrame | np.ndarray) -> np.ndarray:
        window = LocalWindow(batch, np.zeros(len(batch), dtype=np.int64)) if isinstance(batch, np.ndarray) else SparkWindow(batch.withColumn("batch_seq", F.lit(0).cast("long")))
        if self.centroids is None:
            self.centroids = local_kmpp(batch, self.k, np.random.default_rng(self.seed)) if isinstance(window, LocalWindow) else SEEDINGS["kmpp"](window.df, self.k, seed=self.seed)
        counts, sums = window.passes([self.centroids])[0].weighted(np.ones(1))
        old = self.weights * self.decay
        total = old + counts
        some = total > 0
        c = np.asarray(self.centroids, dtype=float).copy()
        c[some] = (old[some, None] * c[some] + sums[some]) / total[some, None]
        self.centroids, self.weights = c, total
        return c
