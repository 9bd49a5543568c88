"""Pairing two sets of weighted centroids: cost of merging each pair, the cheapest one-to-one pairing, and the merged centroids."""

from __future__ import annotations

import warnings
from itertools import permutations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadestream.functions import vectors as V

#: Beyond this many centroids an exact pairing is slow on one machine.
LARGE = 2000


def pair_cost(past: np.ndarray, w_past: np.ndarray, fresh: np.ndarray, w_fresh: np.ndarray) -> np.ndarray:
    """What the error grows by, at least, when each pair is merged into its mean: w w' / (w + w') times the squared distance."""
    d2 = ((past[:, None, :] - fresh[None, :, :]) ** 2).sum(axis=2)
    total = w_past[:, None] + w_fresh[None, :]
    return np.divide(w_past[:, None] * w_fresh[None, :], total, out=np.zeros_like(d2), where=total > 0) * d2


def pair_cost_rows(past: DataFrame, fresh: DataFrame) -> DataFrame:
    """The same for relations (k, c, w): rows i, j, cost. Both sides have K rows."""
    a, b = past.select(F.col("k").alias("i"), F.col("c").alias("ci"), F.col("w").alias("wi")), fresh.select(F.col("k").alias("j"), F.col("c").alias("cj"), F.col("w").alias("wj"))
    total = F.col("wi") + F.col("wj")
    cost = F.when(total > 0, F.col("wi") * F.col("wj") / total * V.sq_dist(F.col("ci"), F.col("cj"))).otherwise(0.0)
    return a.crossJoin(F.broadcast(b)).select("i", "j", cost.alias("cost"))


def solve_assignment(cost: np.ndarray) -> tuple[np.ndarray, float]:
    """The permutation of least total cost and that cost: shortest augmenting paths with dual prices, O(K^3)."""
    cost = np.asarray(cost, dtype=float)
    n = len(cost)
    if cost.shape != (n, n):
        raise ValueError("a pairing needs as many rows as columns")
    if n > LARGE:
        warnings.warn(f"{n} centroids: the exact pairing takes long; solver='greedy' is quick but not optimal", stacklevel=2)
    price_r, price_c = np.zeros(n), np.zeros(n)
    row_of = np.full(n, -1)
    for r in range(n):
        # grow a tree of alternating paths from row r until it meets a free column
        dist = cost[r] - price_r[r] - price_c
        came = np.full(n, r)
        seen = np.zeros(n, dtype=bool)
        while True:
            j = int(np.where(seen, np.inf, dist).argmin())
            seen[j] = True
            if row_of[j] < 0:
                break
            via = cost[row_of[j]] - price_r[row_of[j]] - price_c + dist[j]
            better = ~seen & (via < dist)
            dist[better] = via[better]
            came[better] = row_of[j]
        end, reach = j, dist[j]
        inside = np.flatnonzero(seen)
        for q in inside.tolist():  # keep reduced costs non-negative and tree edges tight
            if q != end:
                price_r[row_of[q]] += reach - dist[q]
                price_c[q] -= reach - dist[q]
        price_r[r] += reach
        while True:  # flip the path
            i = int(came[end])
            nxt = int(np.flatnonzero(row_of == i)[0]) if i != r else -1
            row_of[end] = i
            if i == r:
                break
            row_of[nxt] = -1
            end = nxt
    sigma = np.empty(n, dtype=np.int64)
    sigma[row_of] = np.arange(n)
    return sigma, float(cost[np.arange(n), sigma].sum())


def brute_force_assignment(cost: np.ndarray) -> tuple[np.ndarray, float]:
    n = len(cost)
    if n > 8:
        raise ValueError("enumeration is for up to 8")
    best = min(permutations(range(n)), key=lambda p: (sum(cost[i][p[i]] for i in range(n)), p))
    return np.array(best), float(sum(cost[i][best[i]] for i in range(n)))


def greedy_assignment(cost: np.ndarray) -> tuple[np.ndarray, float]:
    """Cheapest remaining pair first: not optimal."""
    n = len(cost)
    sigma, rows, cols = np.full(n, -1), set(range(n)), set(range(n))
    for at in np.argsort(cost, axis=None, kind="stable").tolist():
        i, j = divmod(at, n)
        if i in rows and j in cols:
            sigma[i] = j
            rows.discard(i)
            cols.discard(j)
    return sigma, float(cost[np.arange(n), sigma].sum())


def identity_assignment(cost: np.ndarray) -> tuple[np.ndarray, float]:
    return np.arange(len(cost)), float(np.trace(cost))


SOLVERS = {"exact": solve_assignment, "greedy": greedy_assignment, "identity": identity_assignment, "brute": brute_force_assignment}


def combine_pairs(past: np.ndarray, w_past: np.ndarray, fresh: np.ndarray, w_fresh: np.ndarray, sigma: np.ndarray) -> np.ndarray:
    """Each pair's weighted mean; the past centroid where neither weighs anything."""
    w0, total = w_fresh[sigma], w_past + w_fresh[sigma]
    out = past.astype(float).copy()
    some = total > 0
    out[some] = (w_past[some, None] * past[some] + w0[some, None] * fresh[sigma][some]) / total[some, None]
    return out


def seed_bound(past: np.ndarray, w_past: np.ndarray, fresh: np.ndarray, w_fresh: np.ndarray, c: np.ndarray, mass: float) -> float:
    """Weighted error of both sets of centroids under c, by the mass of the window."""
    both, w = np.concatenate([past, fresh]), np.concatenate([w_past, w_fresh])
    d2 = ((both[:, None, :] - c[None, :, :]) ** 2).sum(axis=2).min(axis=1)
    return float((w * d2).sum() / mass)


def seed_bound_paired(past: np.ndarray, w_past: np.ndarray, fresh: np.ndarray, w_fresh: np.ndarray, c: np.ndarray, sigma: np.ndarray, mass: float) -> float:
    """The same if centroid k answers for past centroid k and fresh centroid sigma(k)."""
    a = (w_past * ((c - past) ** 2).sum(axis=1)).sum()
    b = (w_fresh[sigma] * ((c - fresh[sigma]) ** 2).sum(axis=1)).sum()
    return float((a + b) / mass)
