"""The experiments: gap of the two errors, and the grid of start policies over forged drifts. Replication is the wide side:
each (dataset, eps, K, m, repetition) is one task that works on a block of points, in memory or its own temporary file; results land
in one fact table."""

from __future__ import annotations

import functools
import itertools
import uuid
from collections.abc import Iterator, Sequence
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadestream.functions.kernels import fading
from fadestream.functions.theory import choose_rho, choose_t_max, drift_gap_interval, drift_gap_interval_finite
from fadestream.operators.blocks import PointBlock
from fadestream.operators.distance import block as rows_of
from fadestream.operators.engine import DriftOracleClusterer, FadingClusterer
from fadestream.operators.features import VIEWS, zscore
from fadestream.operators.forge import DriftForge
from fadestream.operators.measures import MEASUREMENTS
from fadestream.operators.seeding import local_kmpp
from fadestream.sources.window_store import shared_root

METHODS = ["carry", "fresh", "blend", "pair"]


def block_of(spark: SparkSession, sf_dir: str, dataset: str, limit: int = 20_000, scale: bool = True, seed: int = 0) -> DataFrame:
    """dataset, x: up to limit points of a view chosen by hash (the block a cell holds in memory), standardised except unit vectors."""
    d, view = VIEWS[dataset]
    df = view(spark, sf_dir).select("point_id", "x")
    if scale and not dataset.startswith("embed"):
        df = zscore(df, d)
    picked = df.orderBy(F.xxhash64("point_id", F.lit(seed)), "point_id").limit(limit)
    return picked.select(F.lit(dataset).alias("dataset"), "x")


def whole_block(spark: SparkSession, sf_dir: str, dataset: str) -> tuple[DataFrame, int]:
    """dataset, x of every point of a view, standardised except unit vectors, and their number. The view is worked out once, into the shared folder."""
    d, view = VIEWS[dataset]
    raw, path = view(spark, sf_dir).select("x"), shared_root(spark, f"block-{uuid.uuid4().hex}")
    raw.write.parquet(path)
    df = spark.read.schema(raw.schema).parquet(path)
    n = df.count()
    return (df if dataset.startswith("embed") else zscore(df, d)).select(F.lit(dataset).alias("dataset"), "x"), n


def run_cell(x: PointBlock, cell: dict, *, n: int, concepts: int, period: int, tol: float, shared_from: str, start_options: dict) -> list[dict]:
    """One cell: burn-in on the first concept, then `concepts` drifts of `period` batches; every method sees the same batches."""
    eps, k, m, rep = cell["eps"], int(cell["k"]), int(cell["m"]), int(cell["rep"])
    seed = int(np.random.SeedSequence([rep, k, int(eps * 1000), m, abs(hash_of(cell["dataset"]))]).generate_state(1)[0])
    rng = np.random.default_rng(seed)
    rho = choose_rho(eps, period, m, tol)
    t_max = cell.get("t_max") or choose_t_max(rho)
    forge = DriftForge(eps, k, seed % 100_000)
    windows: dict = {}  # the policies hold the same batches
    fades = {name: FadingClusterer(k, rho, t_max, name, seed=seed % 1000, windows=windows, **start_options) for name in METHODS}
    oracle = DriftOracleClusterer(k, seed=seed % 1000, windows={})
    shared = None
    rows: list[dict] = []
    seq = 0

    def draw(block: PointBlock) -> np.ndarray:
        return block.rows(rng.choice(len(block), size=n, replace=n > len(block)))

    def step(batch: np.ndarray, concept: int, index: int, drift_seq: int) -> None:
        nonlocal shared, seq
        seeds = local_kmpp(batch, k, rng)
        given = (*shared, seeds) if shared is not None and shared_from != "independent" else None
        done = {name: f.step(batch, seq, given) for name, f in fades.items()}
        done["reference"] = oracle.step(batch, is_drift=index == 1 and concept > 0, seq=seq, seeds=seeds)
        best = min(METHODS, key=lambda q: (done[q].final_faded, METHODS.index(q))) if shared_from in ("best", "independent") else shared_from
        shared = (done[best].centroids, done[best].sums)
        if concept > 0:
            for name, r in done.items():
                values = {"since_drift": r.since_drift(drift_seq), "distances": float(r.total_distances), "iterations": float(r.iterations)}
                if name != "reference":
                    values |= {"init_faded": r.init_faded, "final_faded": r.final_faded}
                for metric, value in values.items():
                    rows.append(cell | {"rho": rho, "concept_id": concept, "t_index": index, "batch_seq": seq, "method": name, "metric": metric, "value": value})
        seq += 1

    block = x
    for i in range(t_max):
        step(draw(block), 0, i + 1, 0)
    for concept in range(1, concepts + 1):
        block = forge.next(block).points
        first = seq
        for index in range(1, period + 1):
            step(draw(block), concept, index, first)
    return rows


def hash_of(text: str) -> int:
    import zlib

    return zlib.crc32(text.encode())


def run_grid(
    spark: SparkSession, sf_dir: str, datasets: Sequence[str], eps: Sequence[float] = (0.5, 1.0, 2.0), ks: Sequence[int] = (5, 10, 25), ms: Sequence[int] = (2,), reps: int = 1, *, n: int = 500, concepts: int = 10, period: int = 10,
    tol: float = 0.01, shared_from: str = "best", limit: int | None = None, run_id: str = "grid", t_maxes: Sequence[int | None] = (None,), **start_options,  # noqa: ANN003
) -> DataFrame:
    """The fact table of a grid. Every cell is one task over all points of its view (limit: over so many of them, chosen by hash).
    t_maxes: windows instead of the one that rho implies (a column t_max then)."""
    # the views' jobs run side by side, the widest first: some are a single task over documents, which the others' tasks would hold up
    with ThreadPoolExecutor(max(1, len(datasets))) as pool:
        jobs = {d: pool.submit(lambda d: whole_block(spark, sf_dir, d) if limit is None else (block_of(spark, sf_dir, d, limit), limit), d) for d in sorted(datasets, key=lambda d: -VIEWS[d][0])}
        made = [jobs[d].result() for d in datasets]
    blocks = functools.reduce(DataFrame.unionByName, [b for b, _ in made])
    sizes = {d: size for d, (_, size) in zip(datasets, made, strict=True)}
    cells = [(d, float(e), int(k), int(m), r, t) for d in datasets for e in eps for k in ks for m in ms for r in range(reps) for t in t_maxes]
    # the longest cells have the lowest numbers, so they start first
    cells.sort(key=lambda c: -(sizes[c[0]] + 100_000) * VIEWS[c[0]][0] * c[2])
    grid = spark.createDataFrame([(i, c[0]) for i, c in enumerate(cells)], "cell int, dataset string")
    schema = MEASUREMENTS + ("" if tuple(t_maxes) == (None,) else ", t_max int")
    kinds = {"string": pa.string(), "double": pa.float64(), "int": pa.int32(), "long": pa.int64()}
    arrow = [(name, kinds[kind]) for name, kind in map(str.split, schema.split(", "))]

    def points(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray]]:
        for b in batches:
            cell = b.column(0).to_numpy()
            for lo, hi in itertools.pairwise([0, *(np.flatnonzero(np.diff(cell)) + 1).tolist(), len(cell)] if len(cell) else []):
                part = b.column(1).slice(lo, hi - lo)
                yield int(cell[lo]), rows_of(part, len(part[0]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for i, arrays in itertools.groupby(points(batches), key=lambda p: p[0]):
            x = PointBlock()
            for _, a in arrays:
                x.add(a)
            r = dict(zip(("dataset", "eps", "k", "m", "rep", "t_max"), cells[i], strict=True))
            rows = run_cell(x.done(), r, n=n, concepts=concepts, period=period, tol=tol, shared_from=shared_from, start_options=start_options)
            yield from pa.Table.from_pylist([q | {"run_id": run_id} for q in rows], schema=pa.schema(arrow)).to_batches()

    # a partition a cell; sorted, so that a cell's draws don't depend on the order in which points arrive
    dealt = blocks.join(F.broadcast(grid), "dataset").select("cell", "x").repartitionById(len(cells), "cell").sortWithinPartitions("cell", "x")
    return dealt.mapInArrow(run, schema)


def gap_experiment(spark: SparkSession, sf_dir: str, dataset: str = "lineitem4", *, rho: float = 0.676, n: int = 1000, eps: float = 0.5, stored: int = 40, after: int = 20, reps: int = 20, deltas: Sequence[float] = (0.05, 0.32), limit: int = 1_000_000, seed: int = 1) -> DataFrame:
    """rep, t, delta, gap, centre, half_width, lo, hi, centre_finite, half_finite, inside: measured and predicted gap of the two errors, K = 1."""
    block = block_of(spark, sf_dir, dataset, limit).select("x").toArrow()  # bounded by limit
    x = np.asarray(block.column(0).combine_chunks().flatten(), dtype=float).reshape(block.num_rows, -1)
    x = x[np.lexsort(x.T[::-1])]
    moved = DriftForge(eps, 1, seed).next(x).points
    c = x.mean(axis=0)
    d_old, d_new = ((x - c) ** 2).sum(axis=1), ((moved - c) ** 2).sum(axis=1)
    e, u = float(d_old.mean()), float(max(d_old.max(), d_new.max()))
    real_eps = float(d_new.mean() / e - 1)
    shared = spark.sparkContext.broadcast((d_old, d_new))
    schema = "rep int, t int, delta double, gap double, centre double, half_width double, lo double, hi double, centre_finite double, half_finite double, inside boolean"

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        old, new = shared.value
        for f in frames:
            for rep in f["id"].tolist():
                rng = np.random.default_rng([seed, rep])
                sums = [old[rng.integers(0, len(old), n)].mean() for _ in range(stored)]
                rows = []
                for t in range(1, after + 1):
                    sums.append(new[rng.integers(0, len(new), n)].mean())
                    w = fading(np.arange(len(sums)), len(sums) - 1, rho)
                    gap = float(np.mean(sums[-t:]) - (w * sums).sum() / w.sum())
                    for delta in deltas:
                        centre, half, lo, hi = drift_gap_interval(rho, t, n, u, real_eps, e, delta)
                        cf, hf, _, _ = drift_gap_interval_finite([n] * len(sums), t, rho, u, real_eps, e, delta)
                        rows.append((rep, t, delta, gap, centre, half, lo, hi, cf, hf, lo <= gap <= hi))
                yield pd.DataFrame(rows, columns=[c.split()[0] for c in schema.split(", ")])

    return spark.range(reps).repartition(min(reps, 32)).mapInPandas(run, schema)


def rho_tradeoff(gaps: DataFrame) -> DataFrame:
    """rho, t -> mean and variance of the gap: small rho forgets sooner and varies more."""
    return gaps.groupBy("rho", "t").agg(F.avg("gap").alias("mean"), F.var_samp("gap").alias("variance"))
