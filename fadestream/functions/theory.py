"""Closed forms: forget parameter, fading mass, and the interval around the gap of the two errors.

Each function takes plain numbers; `*_column` twins build the same value from Columns.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F


def choose_rho(eps: float, tau: float, m: float, tol: float = 0.01) -> float:
    """The forget parameter for which a drift of size eps weighs tol after tau/m batches; 1 if it is negligible already."""
    return 1.0 if eps <= tol else (tol / eps) ** (m / tau)


def choose_rho_column(eps: Column, tau: Column, m: Column, tol: float = 0.01) -> Column:
    return F.when(eps <= tol, F.lit(1.0)).otherwise(F.pow(F.lit(tol) / eps, m / tau))


def choose_t_max(rho: float, tail: float = 1e-4) -> int:
    """The smallest window whose next batch would weigh at most tail."""
    if rho <= 0:
        return 1
    if rho >= 1:
        raise ValueError("without forgetting no finite window is enough")
    return max(1, math.ceil(math.log(tail) / math.log(rho) - 1e-12))


def window_mass(sizes: Sequence[float], rho: float) -> float:
    """Faded mass of batches given newest first."""
    return sum(n * rho**t for t, n in enumerate(sizes))


def truncation_mass(rho: float, t_max: int, size: float = 1.0) -> float:
    """Mass of all batches older than a window of t_max equal ones, as a share of the infinite mass times size."""
    return size * rho**t_max


def hoeffding_halfwidth(range_sq_sum: float, delta: float) -> float:
    """Half-width at confidence 1 - delta for a sum of independent terms with the given sum of squared ranges."""
    return math.sqrt(range_sq_sum / 2.0 * math.log(2.0 / delta))


def drift_gap_interval(rho: float, t: int, n: float, u: float, eps: float, e: float, delta: float) -> tuple[float, float, float, float]:
    """(centre, half-width, low, high) of since-drift minus faded error, t equal batches of n after the drift, endless past."""
    ranges = u * u / n * ((2.0 * rho**t - 1.0) / t + (1.0 - rho) / (1.0 + rho))
    centre, half = rho**t * eps * e, hoeffding_halfwidth(max(ranges, 0.0), delta)
    return centre, half, centre - half, centre + half


def drift_gap_columns(rho: Column, t: Column, n: Column, u: Column, eps: Column, e: Column, delta: Column) -> tuple[Column, Column]:
    """(centre, half-width) as expressions."""
    ranges = u * u / n * ((F.lit(2.0) * F.pow(rho, t) - 1.0) / t + (F.lit(1.0) - rho) / (F.lit(1.0) + rho))
    return F.pow(rho, t) * eps * e, F.sqrt(F.greatest(ranges, F.lit(0.0)) / 2.0 * F.log(F.lit(2.0) / delta))


def drift_gap_interval_finite(sizes: Sequence[float], t: int, rho: float, u: float, eps: float, e: float, delta: float) -> tuple[float, float, float, float]:
    """The same for a window of batches of any sizes, newest first: each point's share in both errors is counted exactly."""
    m_t, m_x = float(sum(sizes[:t])), window_mass(sizes, rho)
    ranges = u * u * sum(n * ((1.0 / m_t if i < t else 0.0) - rho**i / m_x) ** 2 for i, n in enumerate(sizes))
    older = sum(n * rho**i for i, n in enumerate(sizes) if i >= t) / m_x
    centre, half = eps * e * older, hoeffding_halfwidth(ranges, delta)
    return centre, half, centre - half, centre + half


def drift_gap_equal_window(w: int, t: int, n: float, rho: float, u: float, eps: float, e: float, delta: float) -> tuple[float, float]:
    """(centre, half-width) in closed form for w equal batches, t of them after the drift."""
    past = (rho**t - rho**w) / (1.0 - rho**w)
    ranges = 1.0 / t - 2.0 * (1.0 - rho**t) / (t * (1.0 - rho**w)) + (1.0 - rho) * (1.0 + rho**w) / ((1.0 + rho) * (1.0 - rho**w))
    return eps * e * past, hoeffding_halfwidth(max(ranges, 0.0) * u * u / n, delta)


def drift_gap_by_cluster(counts_after: Sequence[float], u: Sequence[float], e: Sequence[float], t: int, rho: float, eps: float, delta: float) -> list[tuple[int, float, float, float]]:
    """(k, centre, low, high) for each cluster with its own points per batch, bound and error: exact for fixed groups, a guide otherwise."""
    out = []
    for k, (n, bound, err) in enumerate(zip(counts_after, u, e, strict=True)):
        if n > 0:
            centre, _, low, high = drift_gap_interval(rho, t, n, bound, eps, err, delta)
            out.append((k, centre, low, high))
    return out


def distance_cost(method: str, n_new: int, n_window: int, k: int, passes: int, inner_passes: int = 0, drifted: bool = True) -> dict[str, int]:
    """Point-centroid distances by phase for one step of a start policy."""
    out = {"lloyd": passes * n_window * k}
    if method in ("fresh", "blend", "pair") or (method == "reference" and drifted):
        out["seeding"] = n_new * k
    if method == "blend":
        out["inner"] = 2 * k * k * (1 + inner_passes)
    if method == "pair":
        out["pairing"] = k * k
    return out
