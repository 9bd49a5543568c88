"""Error functions over point relations, as one aggregate each, and the same from sums without a scan."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadestream.functions.kernels import Sums
from fadestream.operators.distance import assign


def plain_error(df: DataFrame, centroids: np.ndarray, engine: str = "arrow") -> DataFrame:
    """n, error: mean squared distance to the nearest centroid."""
    return assign(df, centroids, engine).agg(F.count(F.lit(1)).alias("n"), F.avg("d2").alias("error"))


def since_drift_error(df: DataFrame, centroids: np.ndarray, drift_seq: int, engine: str = "arrow") -> DataFrame:
    """m_t, error over the batches from drift_seq on; the predicate reaches the scan."""
    return assign(df.where(F.col("batch_seq") >= drift_seq), centroids, engine).agg(F.count(F.lit(1)).alias("m_t"), F.avg("d2").alias("error"))


def _weighted(df: DataFrame, cur: int, rho: float) -> DataFrame:
    return df.withColumn("w", F.pow(F.lit(float(rho)), (F.lit(cur) - F.col("batch_seq")).cast("double")))


def faded_error(df: DataFrame, centroids: np.ndarray, rho: float, cur: int, t_max: int | None = None, engine: str = "arrow") -> DataFrame:
    """mass, error with weight rho^age; both parts over the same retained batches. rho = 1 is unfaded, t_max = 1 the newest batch only."""
    kept = df.where(F.col("batch_seq") <= cur)
    if t_max is not None:
        kept = kept.where(F.col("batch_seq") > cur - t_max)
    return _weighted(assign(kept, centroids, engine), cur, rho).agg(F.sum("w").alias("mass"), (F.sum(F.col("w") * F.col("d2")) / F.sum("w")).alias("error"))


def faded_error_split(df: DataFrame, centroids: np.ndarray, rho: float, cur: int, engine: str = "arrow") -> DataFrame:
    """Masses and errors of the newest batch and of the older ones, and their recombination, in one pass."""
    part = _weighted(assign(df.where(F.col("batch_seq") <= cur), centroids, engine), cur, rho)
    new = F.col("batch_seq") == cur
    sums = part.agg(
        F.sum(F.when(new, F.col("w"))).alias("mass_new"), F.sum(F.when(~new, F.col("w"))).alias("mass_old"), F.sum(F.when(new, F.col("w") * F.col("d2"))).alias("s_new"), F.sum(F.when(~new, F.col("w") * F.col("d2"))).alias("s_old")
    )
    e_new, e_old = F.col("s_new") / F.col("mass_new"), F.col("s_old") / F.col("mass_old")
    total = F.col("mass_new") + F.col("mass_old")
    return sums.select("mass_new", "mass_old", e_new.alias("error_new"), e_old.alias("error_old"), (F.col("mass_old") / total * e_old + F.col("mass_new") / total * e_new).alias("recombined"))


def drift_magnitude(before: DataFrame, after: DataFrame, centroids: np.ndarray, engine: str = "arrow") -> DataFrame:
    """ratio_minus_1: how much larger the error of the second relation is under the same centroids."""
    a = assign(before.select("x"), centroids, engine).agg(F.avg("d2").alias("a"))
    b = assign(after.select("x"), centroids, engine).agg(F.avg("d2").alias("b"))
    return a.crossJoin(F.broadcast(b)).select((F.col("b") / F.col("a") - 1).alias("ratio_minus_1"))  # one row each


def sse_from_sums(sums: Sums, centroids: np.ndarray) -> np.ndarray:
    """Squared error per (batch, cluster) of any centroids under an unchanged assignment: scatter about the mean plus the mean's offset."""
    n = np.maximum(sums.n, 1e-300)
    mean = sums.sx / n[:, :, None]
    scatter = np.maximum(sums.sxx - sums.n * (mean**2).sum(axis=2), 0.0)
    return scatter + sums.n * ((mean - centroids[None, :, :]) ** 2).sum(axis=2)


def within_scatter(sums: Sums, w: np.ndarray) -> float:
    """Weighted scatter of the points about their clusters' weighted means."""
    counts, sx = sums.weighted(w)
    some = counts > 0
    return float((w[:, None] * sums.sxx).sum() - ((sx[some] ** 2).sum(axis=1) / counts[some]).sum())
