"""The four start policies and what they need: fresh centroids of the newest batch, weights of both sets of centroids."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from fadestream.functions.kernels import Sums, fading
from fadestream.operators.lloyd import Window, lloyd, lloyd_points
from fadestream.operators.matching import SOLVERS, combine_pairs, pair_cost, seed_bound
from fadestream.operators.seeding import fill, local_forgy, local_kmpp


@dataclass
class Centres:
    """Centroids with weights."""

    c: np.ndarray
    w: np.ndarray


@dataclass
class Start:
    """Where Lloyd begins, and the distances spent to get there."""

    c: np.ndarray
    distances: int
    detail: dict


def past_weights(sums: Sums, newest: int, rho: float, t_max: int | None) -> np.ndarray:
    """Faded counts of the retained older batches under the previous clustering: no point is touched."""
    keep = sums.seqs < newest
    if t_max is not None:
        keep &= sums.seqs > newest - t_max
    kept = sums.keep(keep)
    return fading(kept.seqs, newest, rho) @ kept.n


def past_centres(c: np.ndarray, sums: Sums, newest: int, rho: float, t_max: int | None, recenter: bool) -> Centres:
    """The previous centroids with their weights; recenter makes them the faded means of what is still retained."""
    keep = sums.seqs < newest
    if t_max is not None:
        keep &= sums.seqs > newest - t_max
    kept = sums.keep(keep)
    w = fading(kept.seqs, newest, rho)
    counts, sx = w @ kept.n, np.tensordot(w, kept.sx, axes=1)
    out = np.asarray(c, dtype=float).copy()
    if recenter:
        some = counts > 0
        out[some] = sx[some] / counts[some][:, None]
    return Centres(out, counts)


def fresh_centres(window: Window, seeds: np.ndarray, refine: str = "none", max_iter: int = 100) -> tuple[Centres, int]:
    """Seeds of the newest batch with the counts of their neighbourhoods, and the distances that refining took.

    refine: none keeps the seeds; mean moves each to the mean of its points (counts as taken); lloyd converges on the batch.
    The counts come with the distances of the seeding's last round.
    """
    if refine == "lloyd":
        r = lloyd(window, seeds, max_iter=max_iter)
        return Centres(r.centroids, r.sums.n.sum(axis=0)), r.distances
    s = window.passes([seeds])[0]
    counts, sx = s.weighted(np.ones(len(s.seqs)))
    c = seeds.copy()
    if refine == "mean":
        c[counts > 0] = sx[counts > 0] / counts[counts > 0][:, None]
    elif refine != "none":
        raise ValueError(f"unknown refine {refine}")
    return Centres(c, counts), 0


@dataclass
class CarryOver:
    """Start from the previous centroids."""

    name = "carry"

    def start(self, past: Centres, fresh: Centres, mass: float, rng: np.random.Generator) -> Start:
        return Start(past.c.copy(), 0, {})


@dataclass
class FreshSeed:
    """Start from the seeds of the newest batch."""

    name = "fresh"

    def start(self, past: Centres, fresh: Centres, mass: float, rng: np.random.Generator) -> Start:
        return Start(fresh.c.copy(), 0, {})


@dataclass
class BlendSeed:
    """Cluster both sets of centroids together by weight. inner_seed: kmpp, forgy, past, fresh or pair; restarts keep the least bound."""

    inner_seed: str = "kmpp"
    restarts: int = 1
    max_iter: int = 100
    name = "blend"

    def start(self, past: Centres, fresh: Centres, mass: float, rng: np.random.Generator) -> Start:
        k = len(past.c)
        x, w = np.concatenate([past.c, fresh.c]), np.concatenate([past.w, fresh.w])
        x, w = x[w > 0], w[w > 0]
        if len(np.unique(x, axis=0)) < k:
            pool = np.concatenate([fresh.c, past.c])
            _, first = np.unique(pool, axis=0, return_index=True)
            return Start(fill(pool[np.sort(first)][:k], k), 0, {"inner_passes": 0})
        best, spent = None, 0
        for _ in range(self.restarts if self.inner_seed in ("kmpp", "forgy") else 1):
            if self.inner_seed == "pair":
                pair = PairSeed().start(past, fresh, mass, rng)
                c0, cost = pair.c, pair.distances
            elif self.inner_seed in ("past", "fresh"):
                c0, cost = (past.c if self.inner_seed == "past" else fresh.c), 0
            else:
                c0, cost = (local_kmpp(x, k, rng, weight=w), len(x) * k) if self.inner_seed == "kmpp" else (local_forgy(x, k, rng), 0)
            r = lloyd_points(x, w, c0, self.max_iter)
            spent += cost + len(x) * k * r.iterations
            f = seed_bound(past.c, past.w, fresh.c, fresh.w, r.centroids, mass)
            if best is None or f < best[0]:
                best = (f, r)
        return Start(best[1].centroids, spent, {"inner_passes": best[1].iterations, "bound": best[0]})


@dataclass
class PairSeed:
    """Pair the two sets one to one at the least cost and merge each pair. solver: exact, greedy or identity."""

    solver: str = "exact"
    name = "pair"

    def start(self, past: Centres, fresh: Centres, mass: float, rng: np.random.Generator) -> Start:
        cost = pair_cost(past.c, past.w, fresh.c, fresh.w)
        sigma, value = SOLVERS[self.solver](cost)
        return Start(combine_pairs(past.c, past.w, fresh.c, fresh.w, sigma), cost.size, {"sigma": sigma.tolist(), "bound": value / mass if mass else float("nan")})


POLICIES = {"carry": CarryOver, "fresh": FreshSeed, "blend": BlendSeed, "pair": PairSeed}
