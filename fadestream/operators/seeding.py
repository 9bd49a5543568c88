"""Seedings. Draws come from MD5 of (point id, round), so they are portable, repeatable and independent of partitioning.

Sequential sampling proportional to a weight is done as an exponential race: the point with the least -ln(u)/weight wins,
which is exactly the law wanted and needs one mergeable minimum instead of a running total.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fadestream.functions import vectors as V
from fadestream.functions.kernels import nearest
from fadestream.operators.distance import UNROLL_MAX, assign
from fadestream.operators.lloyd import lloyd_points


def _u(seed: int, step: int | str) -> Column:
    return V.uniform_from(F.col("point_id"), F.lit(f"{seed}.{step}"))


def local_uniform(point_id: object, seed: int, step: int | str) -> float:
    """The number that _u gives for the same point."""
    return (int(hashlib.md5(f"{point_id}-{seed}.{step}".encode()).hexdigest()[:8], 16) + 0.5) / 4294967296.0


def _array(rows: list) -> np.ndarray:
    return np.array([r["x"] for r in rows], dtype=float)


def fill(c: np.ndarray, k: int) -> np.ndarray:
    """k centroids from fewer distinct points, in turn."""
    return c if len(c) >= k else c[np.arange(k) % len(c)]


def seed_forgy(df: DataFrame, k: int, seed: int = 0) -> np.ndarray:
    """k points at random: the least hashes, by a top-k heap instead of a sort."""
    rows = df.select("x", _u(seed, "forgy").alias("u"), "point_id").orderBy("u", "point_id").limit(k).collect()
    return fill(_array(rows), k)


def with_d2(df: DataFrame, c: np.ndarray) -> DataFrame:
    """df with __d, the squared distance to the nearest of c: generated code for few coordinates, blocks for many."""
    if c.size <= UNROLL_MAX:
        return df.withColumn("__d", V.nearest_struct(F.col("x"), c)["d2"])
    return assign(df, c).withColumnRenamed("d2", "__d").drop("k")


def kmpp_picks(df: DataFrame, k: int, seed: int = 0, power: int = 2, weight_col: str | None = None) -> list[tuple[object, list[float]]]:
    """(point_id, x) of each seed in order. Sequential sampling with probability proportional to weight * distance^power (2: the published law, 1: the plain distance).

    One scan and one row to the driver a round; the distance so far is carried in a cached column by the caller's persist if
    wanted, else recomputed from the few seeds.
    """
    w = F.col(weight_col).cast("double") if weight_col else F.lit(1.0)
    chosen: list[tuple[object, list[float]]] = []
    for r in range(k):
        base = df
        load = w
        if chosen:
            base = with_d2(df, np.array([x for _, x in chosen]))
            base = (base if power == 2 else base.withColumn("__d", F.pow("__d", F.lit(power / 2.0)))).where("__d > 0")
            load = w * F.col("__d")
        race = F.min_by(F.struct("point_id", "x"), F.struct(-F.log(_u(seed, r)) / load, F.col("point_id"))).alias("p")
        row = base.where(w > 0).agg(race).first()["p"]
        if row is None:
            break
        chosen.append((row["point_id"], [float(v) for v in row["x"]]))
    if not chosen:
        raise ValueError("no points to seed from")
    return chosen


def seed_kmpp(df: DataFrame, k: int, seed: int = 0, power: int = 2, weight_col: str | None = None) -> np.ndarray:
    """The seeds of kmpp_picks; fewer distinct points than k are used in turn."""
    return fill(np.array([x for _, x in kmpp_picks(df, k, seed, power, weight_col)]), k)


def local_kmpp(x: np.ndarray, k: int, rng: np.random.Generator, power: int = 2, weight: np.ndarray | None = None) -> np.ndarray:
    """The same law for points in memory."""
    w = np.ones(len(x)) if weight is None else weight.astype(float)
    chosen = np.empty((0, x.shape[1]))
    d2 = np.full(len(x), np.inf)
    for _ in range(k):
        load = w if not len(chosen) else w * np.power(d2, power / 2.0)
        some = load > 0
        if not some.any():
            break
        key = np.full(len(x), np.inf)
        key[some] = rng.exponential(size=int(some.sum())) / load[some]
        pick = x[int(key.argmin())]
        chosen = np.vstack([chosen, pick])
        d2 = np.minimum(d2, ((x - pick) ** 2).sum(axis=1))
    return fill(chosen, k)


def local_forgy(x: np.ndarray, k: int, rng: np.random.Generator) -> np.ndarray:
    return fill(x[rng.permutation(len(x))[:k]], k)


def parallel_round(df: DataFrame, chosen: np.ndarray, ell: float, seed: int, step: int) -> tuple[DataFrame, float]:
    """One oversampling round: the points that pass their own coin with probability min(1, ell * D^2 / total), and the total."""
    near = with_d2(df, chosen)
    phi = near.agg(F.sum("__d")).first()[0] or 0.0
    picked = near.where((F.col("__d") > 0) & (_u(seed, f"par{step}") < F.least(F.lit(1.0), F.lit(ell) * F.col("__d") / F.lit(max(phi, 1e-300)))))
    return picked.drop("__d"), phi


def _thinned(chosen: np.ndarray, counts: np.ndarray, k: int, seed: int) -> np.ndarray:
    """k seeds from the candidates and how many points are nearest to each."""
    return lloyd_points(chosen, counts, local_kmpp(chosen, k, np.random.default_rng(seed), weight=counts)).centroids


def seed_parallel(df: DataFrame, k: int, ell: float | None = None, rounds: int = 5, seed: int = 0) -> np.ndarray:
    """Oversampling in a few rounds, then weighted sequential sampling among the candidates: a handful of scans instead of k."""
    ell = ell or 2.0 * k
    chosen = seed_kmpp(df, 1, seed)
    for r in range(rounds):
        picked, phi = parallel_round(df, chosen, ell, seed, r)
        if phi <= 0:
            break
        rows = picked.select("x").collect()  # about ell points
        if rows:
            chosen = np.unique(np.vstack([chosen, _array(rows)]), axis=0)
    counts = {r["k"]: r["count"] for r in assign(df.select("x"), chosen).groupBy("k").count().collect()}
    w = np.array([counts.get(i, 0) for i in range(len(chosen))], dtype=float)
    return _thinned(chosen, w, k, seed)


def seed_mcmc(df: DataFrame, k: int, chain: int = 200, seed: int = 0, proposal: str = "uniform") -> np.ndarray:
    """A Markov chain a seed instead of a scan a seed. Proposals: uniform, or a mix of uniform and squared distance to the first seed.

    All proposals are drawn in one scan (k * chain points); the chains run on the driver.
    """
    first = seed_kmpp(df, 1, seed)
    want = max(1, (k - 1) * chain)
    u = _u(seed, "mc")
    if proposal == "uniform":
        rows = df.select("x", "point_id", F.lit(1.0).alias("q"), (-F.log(u)).alias("key")).orderBy("key", "point_id").limit(want).collect()
    else:
        stats = df.agg(F.sum(V.sq_dist_unrolled(F.col("x"), first[0])).alias("phi"), F.count(F.lit(1)).alias("n")).first()
        q = F.lit(0.5) * V.sq_dist_unrolled(F.col("x"), first[0]) / F.lit(max(stats["phi"] or 0.0, 1e-300)) + F.lit(0.5 / max(stats["n"], 1))
        rows = df.select("x", "point_id", q.alias("q"), (-F.log(u) / q).alias("key")).orderBy("key", "point_id").limit(want).collect()
    return _chains(first, _array(rows), np.array([r["q"] for r in rows]), k, chain, seed)


def _chains(first: np.ndarray, x: np.ndarray, q: np.ndarray, k: int, chain: int, seed: int) -> np.ndarray:
    """One chain a seed over the proposals x, which were drawn in proportion to q."""
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(x))
    chosen, at = first.copy(), 0
    for _ in range(1, k):
        d = None
        for _ in range(chain):
            j = order[at % len(order)]
            at += 1
            dj = float(((chosen - x[j]) ** 2).sum(axis=1).min()) / q[j]
            if d is None or d == 0 or dj / d > rng.random():
                cur, d = j, dj
        chosen = np.vstack([chosen, x[cur]])
    return fill(chosen, k)


class HeldPoints:
    """Points in memory with the numbers that a scan would draw for them: of the same ids, the seedings below pick what theirs pick."""

    def __init__(self, x: np.ndarray, ids: list, seed: int = 0) -> None:
        order = sorted(range(len(ids)), key=ids.__getitem__)  # so that the first of equal keys has the least id
        self.x, self.ids, self.seed = x[order], [f"{ids[i]}-".encode() for i in order], seed

    def u(self, step: int | str) -> np.ndarray:
        end = f"{self.seed}.{step}".encode()
        heads = b"".join([hashlib.md5(i + end).digest()[:4] for i in self.ids])
        return (np.frombuffer(heads, dtype=">u4") + 0.5) / 4294967296.0

    def d2(self, c: np.ndarray) -> np.ndarray:
        return ((self.x - c) ** 2).sum(axis=1)


def held_forgy(p: HeldPoints, k: int) -> np.ndarray:
    return fill(p.x[np.argsort(p.u("forgy"), kind="stable")[:k]], k)


def held_kmpp(p: HeldPoints, k: int) -> np.ndarray:
    chosen, load = [], np.ones(len(p.x))
    for r in range(k):
        some = np.flatnonzero(load > 0)
        if not len(some):
            break
        pick = p.x[some[(-np.log(p.u(r)[some]) / load[some]).argmin()]]
        load = np.minimum(load, p.d2(pick)) if chosen else p.d2(pick)
        chosen.append(pick)
    return fill(np.array(chosen), k)


def held_parallel(p: HeldPoints, k: int, ell: float | None = None, rounds: int = 5) -> np.ndarray:
    ell, chosen = ell or 2.0 * k, held_kmpp(p, 1)
    d = p.d2(chosen[0])
    for r in range(rounds):
        if not d.sum() > 0:
            break
        picked = p.x[(d > 0) & (p.u(f"par{r}") < np.minimum(1.0, ell * d / d.sum()))]
        for c in picked:
            d = np.minimum(d, p.d2(c))
        chosen = np.unique(np.vstack([chosen, picked]), axis=0)
    return _thinned(chosen, counts_near(p.x, chosen), k, p.seed)


def held_mcmc(p: HeldPoints, k: int, chain: int = 200) -> np.ndarray:
    order = np.argsort(-np.log(p.u("mc")), kind="stable")[: max(1, (k - 1) * chain)]
    return _chains(held_kmpp(p, 1), p.x[order], np.ones(len(order)), k, chain, p.seed)


HELD_SEEDINGS = {"kmpp": held_kmpp, "forgy": held_forgy, "parallel": held_parallel, "mcmc": held_mcmc}
SEEDINGS = {"kmpp": seed_kmpp, "forgy": seed_forgy, "parallel": seed_parallel, "mcmc": seed_mcmc}


def kmeans(df: DataFrame, k: int, init: str = "kmpp", seed: int = 0, max_iter: int = 100):  # noqa: ANN201
    """Seeding plus Lloyd on a static relation."""
    from fadestream.operators.lloyd import lloyd, window_of

    points = df if "batch_seq" in df.columns else df.withColumn("batch_seq", F.lit(0).cast("long"))
    return lloyd(window_of(points), SEEDINGS[init](points, k, seed=seed), max_iter=max_iter)


def counts_near(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.bincount(nearest(x, c)[0], minlength=len(c)).astype(float)


