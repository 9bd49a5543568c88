"""Related published methods around the choice of K: validity indices from sums, splitting by an information criterion or by normality."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadestream.functions.kernels import Sums
from fadestream.operators.lloyd import lloyd, window_of
from fadestream.operators.seeding import seed_kmpp


def _totals(sums: Sums) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    n, sx, sse = sums.n.sum(axis=0), sums.sx.sum(axis=0), sums.sse.sum(axis=0)
    some = n > 0
    return n[some], sx[some], sse[some]


def calinski_harabasz(sums: Sums) -> float:
    """Between over within scatter, each by its degrees of freedom; sums must be those of the final centroids."""
    n, sx, sse = _totals(sums)
    k, total = len(n), n.sum()
    mean = sx.sum(axis=0) / total
    between = (n * ((sx / n[:, None] - mean) ** 2).sum(axis=1)).sum()
    return float(between / (k - 1) / (sse.sum() / (total - k)))


def davies_bouldin(sums: Sums, centroids: np.ndarray) -> float:
    """Mean over clusters of the worst ratio of spreads to separation; spread is the root mean squared distance."""
    n = sums.n.sum(axis=0)
    some = n > 0
    s = np.sqrt(sums.sse.sum(axis=0)[some] / n[some])
    c = centroids[some]
    d = np.sqrt(((c[:, None, :] - c[None, :, :]) ** 2).sum(axis=2))
    ratio = np.where(d > 0, (s[:, None] + s[None, :]) / np.where(d > 0, d, 1), -np.inf)
    return float(ratio.max(axis=1).mean())


def simplified_silhouette(df: DataFrame, centroids: np.ndarray) -> DataFrame:
    """value: the silhouette with distances to centroids in place of points; one scan."""
    from fadestream.functions import vectors as V

    every = F.array_sort(F.array(*((V.sq_dist_unrolled(F.col("x"), c) if centroids.size <= 100 else V.sq_dist(F.col("x"), V.vec(c))) for c in centroids)))
    a, b = F.sqrt(F.get(every, 0)), F.sqrt(F.get(every, 1))
    return df.select(F.when(b == 0, 0.0).otherwise((b - a) / b).alias("s")).agg(F.avg("s").alias("value"))


def silhouette(x: np.ndarray, k: np.ndarray) -> float:
    """The exact index of a sample in memory: all pairwise distances."""
    d = np.sqrt(np.maximum(((x[:, None, :] - x[None, :, :]) ** 2).sum(axis=2), 0))
    labels = np.unique(k)
    sums = np.stack([d[:, k == c].sum(axis=1) for c in labels], axis=1)
    counts = np.array([(k == c).sum() for c in labels])
    own = np.searchsorted(labels, k)
    rows = np.arange(len(x))
    a = sums[rows, own] / np.maximum(counts[own] - 1, 1)
    others = sums / counts
    others[rows, own] = np.inf
    b = others.min(axis=1)
    s = np.where(counts[own] > 1, (b - a) / np.maximum(np.maximum(a, b), 1e-300), 0.0)
    return float(s.mean())


def bic(n: np.ndarray, sse: float, d: int) -> float:
    """Log likelihood of spherical Gaussians with one variance, less half the parameters times log n (larger is better)."""
    total, k = n.sum(), len(n)
    if total <= k:
        return -math.inf
    var = max(sse / (d * (total - k)), 1e-300)
    like = (n[n > 0] * np.log(n[n > 0] / total)).sum() - total * d / 2 * math.log(2 * math.pi * var) - d * (total - k) / 2
    return float(like - (k - 1 + d * k + 1) / 2 * math.log(total))


def _normal_statistic(values: DataFrame) -> float:
    """Anderson-Darling statistic of all rows of one column z against a normal law with estimated moments: ranks come from a range exchange and counts of its partitions."""
    n, mean, std = values.agg(F.count("z"), F.avg("z"), F.stddev_samp("z")).first()
    dealt = values.repartitionByRange("z").sortWithinPartitions("z").withColumn("part", F.spark_partition_id()).persist()
    starts, upto = {}, 0
    for part, count in sorted(tuple(r) for r in dealt.groupBy("part").count().collect()):
        starts[part], upto = upto, upto + count

    def terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, total = None, 0.0
        for b in batches:
            if not b.num_rows:
                continue
            at = starts[b.column(1)[0].as_py()] if at is None else at
            z = (b.column(0).to_numpy(zero_copy_only=False) - mean) / max(std, 1e-300)
            cdf = np.clip([0.5 * (1 + math.erf(v / math.sqrt(2))) for v in z], 1e-12, 1 - 1e-12)
            i = np.arange(at + 1, at + len(z) + 1)
            total += float(((2 * i - 1) * np.log(cdf) + (2 * (n - i) + 1) * np.log(1 - cdf)).sum())
            at += len(z)
        yield pa.RecordBatch.from_pydict({"t": [total]})

    a2 = -n - dealt.mapInArrow(terms, "t double").agg(F.sum("t")).first()[0] / n
    dealt.unpersist()
    return float(a2 * (1 + 4 / n - 25 / n**2))


def choose_k(df: DataFrame, k_max: int = 16, method: str = "bic_split", seed: int = 0, critical: float = 1.8692) -> tuple[int, np.ndarray]:
    """Split clusters in two while it pays. bic_split: the information criterion of the part improves; normal_split: the part,
    projected on the line between its halves, fails a normality test on all its points; or the best of an index
    over 2..k_max: silhouette, davies_bouldin, calinski_harabasz. Returns K and centroids.
    """
    from fadestream.operators.distance import assign

    df = df.persist()
    d = len(df.first()["x"])
    if method in ("silhouette", "davies_bouldin", "calinski_harabasz"):
        scores = []
        for k in range(2, k_max + 1):
            r = lloyd(window_of(df), seed_kmpp(df, k, seed), max_iter=30)
            if method == "silhouette":
                value = simplified_silhouette(df, r.centroids).first()[0]
            else:
                value = calinski_harabasz(r.sums) if method == "calinski_harabasz" else -davies_bouldin(r.sums, r.centroids)
            scores.append((value, -k, r.centroids))
        best = max(scores, key=lambda t: t[:2])
        return len(best[2]), best[2]
    c = df.agg(*(F.avg(F.col("x")[j]) for j in range(d))).first()
    centroids = np.array([list(c)], dtype=float)
    settled: set[tuple] = set()
    while len(centroids) < k_max:
        parts, grew = [], False
        tagged = assign(df, centroids)
        for k in range(len(centroids)):
            mark = tuple(np.round(centroids[k], 9))
            part = tagged.where(F.col("k") == k).drop("k", "d2")
            if mark in settled or len(parts) + len(centroids) - k >= k_max or part.limit(8).count() < 8:
                parts.append(centroids[k])
                continue
            two = lloyd(window_of(part), seed_kmpp(part, 2, seed + k), max_iter=30)
            n = two.sums.n.sum(axis=0)
            if method == "bic_split":
                one = lloyd(window_of(part), centroids[k : k + 1], max_iter=2)
                split = bic(n, float(two.sums.sse.sum()), d) > bic(one.sums.n.sum(axis=0), float(one.sums.sse.sum()), d)
            else:
                line = two.centroids[1] - two.centroids[0]
                z = sum((F.col("x")[j] * float(v) for j, v in enumerate(line / max(line @ line, 1e-300))), F.lit(0.0))
                split = bool(line @ line) and _normal_statistic(part.select(z.alias("z"))) > critical
            if split and (n > 0).all():
                parts.extend(two.centroids)
                grew = True
            else:
                settled.add(mark)
                parts.append(centroids[k])
        centroids = lloyd(window_of(df), np.array(parts), max_iter=30).centroids
        if not grew:
            break
    return len(centroids), centroids
