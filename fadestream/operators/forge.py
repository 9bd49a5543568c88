"""Drifts of controlled strength: every cluster of a block is moved along its own random direction until the mean squared
distance to the old centroids has grown by the factor wanted."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadestream.functions import vectors as V
from fadestream.functions.kernels import nearest
from fadestream.operators.blocks import PointBlock
from fadestream.operators.distance import assign, block
from fadestream.operators.lloyd import LocalWindow, lloyd
from fadestream.operators.seeding import kmeans, local_kmpp
from fadestream.sources.window_store import shared_root


def unit_directions(k: int, d: int, seed: int) -> np.ndarray:
    """k random directions of length 1."""
    g = np.random.default_rng(seed).normal(size=(k, d))
    return g / np.linalg.norm(g, axis=1, keepdims=True)


@dataclass
class Magnitude:
    alpha: float
    ratio: float
    steps: int
    converged: bool


def first_alpha(error: float, eps: float, k: int, n: int, scale: str) -> float:
    """Scale of the steps. sum: the error counts as a sum over points; literal: as the mean it is, which makes tiny steps."""
    return float(np.sqrt(eps * error / k)) if scale == "sum" else float(np.sqrt(eps * error / (k * n)))


def search_alpha(trial, error: float, eps: float, k: int, n: int, *, tol: float = 0.05, scale: str = "sum", max_steps: int = 60, mode: str = "step") -> Magnitude:  # noqa: ANN001
    """Find the length of the move. trial(alphas) gives the errors at several lengths in one go.

    step: additive corrections by the relative error; grid: brackets and narrows with a few lengths a scan.
    """
    target = (1 + eps) * error
    if mode == "grid":
        low, high = np.sqrt(eps * error) * 0.5, np.sqrt(eps * error) * 2.0
        for step in range(1, max_steps + 1):
            alphas = np.linspace(low, high, 9)
            ratios = np.asarray(trial(alphas)) / target
            best = int(np.abs(ratios - 1).argmin())
            if abs(ratios[best] - 1) < tol / 5:
                return Magnitude(float(alphas[best]), float(ratios[best] * (1 + eps)), step, True)
            over = np.flatnonzero(ratios >= 1)
            if not len(over):
                low, high = high, high * 2
            elif over[0] == 0:
                low, high = low / 2, float(alphas[0])
            else:
                low, high = float(alphas[over[0] - 1]), float(alphas[over[0]])
        return Magnitude(float(alphas[best]), float(ratios[best] * (1 + eps)), max_steps, bool(abs(ratios[best] - 1) < tol))
    unit = first_alpha(error, eps, k, n, scale)
    alpha, ratio = unit, 0.0
    for step in range(1, max_steps + 1):
        ratio = float(np.asarray(trial(np.array([alpha])))[0]) / target
        if abs(ratio - 1) < tol:
            return Magnitude(alpha, ratio * (1 + eps), step, True)
        alpha = alpha - (ratio - 1) * unit
    return Magnitude(alpha, ratio * (1 + eps), max_steps, False)


@dataclass
class Forged:
    points: object
    centroids: np.ndarray
    xi: np.ndarray
    magnitude: Magnitude


def _written(df: DataFrame, label: str) -> DataFrame:
    path = f"{shared_root(df.sparkSession, 'forge')}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class DriftForge:
    """next(block): the block after a drift of size eps, as array, relation or PointBlock (the same kind as given; the last is moved itself), with what was done."""

    def __init__(self, eps: float, k: int, seed: int = 0, *, scale: str = "sum", mode: str = "step", tol: float = 0.05, max_steps: int = 60) -> None:
        self.eps, self.k, self.seed, self.scale, self.mode, self.tol, self.max_steps = eps, k, seed, scale, mode, tol, max_steps
        self.count = 0

    def next(self, block: np.ndarray | PointBlock | DataFrame) -> Forged:
        self.count += 1
        rng_seed = self.seed * 1009 + self.count
        if isinstance(block, np.ndarray):
            window = LocalWindow(block, np.zeros(len(block), dtype=np.int64))
            c = lloyd(window, local_kmpp(block, self.k, np.random.default_rng(rng_seed))).centroids
            k, d2 = nearest(block, c)
            xi = unit_directions(self.k, block.shape[1], rng_seed)
            trial = lambda alphas: [nearest(block + a * xi[k], c)[1].mean() for a in alphas]
            m = search_alpha(trial, float(d2.mean()), self.eps, self.k, len(block), tol=self.tol, scale=self.scale, mode=self.mode, max_steps=self.max_steps)
            return Forged(block + m.alpha * xi[k], c, xi, m)
        if isinstance(block, PointBlock):
            r = lloyd(block, block.kmpp(self.k, np.random.default_rng(rng_seed)))
            xi = unit_directions(self.k, block.d, rng_seed)
            m = search_alpha(lambda alphas: block.errors(xi, alphas), r.errors[-1], self.eps, self.k, len(block), tol=self.tol, scale=self.scale, mode=self.mode, max_steps=self.max_steps)
            block.move(m.alpha * xi)
            return Forged(block, r.centroids, xi, m)
        # written once each: every pass reads plain points, and a concept's plan doesn't hold those of all before it
        block = _written(block, "block")
        c = kmeans(block, self.k, seed=rng_seed).centroids
        tagged = _written(assign(block, c), "tagged")
        stats = tagged.agg(F.avg("d2").alias("e"), F.count(F.lit(1)).alias("n")).first()
        xi = unit_directions(self.k, c.shape[1], rng_seed)
        trial = lambda alphas: trial_errors(tagged, c, xi, alphas)
        m = search_alpha(trial, stats["e"], self.eps, self.k, stats["n"], tol=self.tol, scale=self.scale, mode="grid" if self.mode == "grid" else self.mode, max_steps=self.max_steps)
        moved = shift_concept(tagged.drop("d2"), xi, m.alpha).select(*block.columns)
        return Forged(moved, c, xi, m)


def shift_concept(tagged: DataFrame, xi: np.ndarray, alpha: float) -> DataFrame:
    """Points with their cluster k moved by alpha times the cluster's direction: K rows are broadcast."""
    rows = [(k, [float(alpha * v) for v in xi[k]]) for k in range(len(xi))]
    move = tagged.sparkSession.createDataFrame(rows, "k int, move array<double>")
    return tagged.join(F.broadcast(move), "k").withColumn("x", V.vec_add(F.col("x"), F.col("move"))).drop("move")


def trial_errors(tagged: DataFrame, c: np.ndarray, xi: np.ndarray, alphas: np.ndarray) -> list[float]:
    """Mean error of the block moved by each length, all in one scan: each task sends a sum for each length."""
    n_alpha = len(alphas)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, n = np.zeros(n_alpha), 0
        for b in batches:
            k, x = b.column(0).to_numpy(zero_copy_only=False), block(b.column(1), c.shape[1])
            n += len(x)
            for i, a in enumerate(alphas):
                sums[i] += nearest(x + a * xi[k], c)[1].sum()
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(n_alpha, dtype=np.int32)), pa.array(sums), pa.array(np.full(n_alpha, n))], names=["i", "s", "n"])

    rows = tagged.select("k", "x").mapInArrow(run, "i int, s double, n long").groupBy("i").agg((F.sum("s") / F.sum("n")).alias("e")).orderBy("i").collect()
    return [r["e"] for r in rows]
