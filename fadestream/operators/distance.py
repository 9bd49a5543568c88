"""Assignment of points to centroids and the one pass over a window that everything else is made from."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadestream.functions import vectors as V
from fadestream.functions.kernels import Sums, nearest, nearest_two, sums_of

#: Centroids with more coordinates in all than this are unrolled no more: the plan would get too large.
UNROLL_MAX = 100


def block(column: pa.Array, d: int) -> np.ndarray:
    """An Arrow list column as an (n, d) array without a copy per row."""
    return np.asarray(column.flatten(), dtype=float).reshape(-1, d)


def centroid_rows(df: DataFrame, centroids: np.ndarray) -> DataFrame:
    """The centroids as a relation (k, c)."""
    return df.sparkSession.createDataFrame([(k, [float(v) for v in c]) for k, c in enumerate(centroids)], "k int, c array<double>")


def assign(df: DataFrame, centroids: np.ndarray, engine: str = "arrow") -> DataFrame:
    """df with k (nearest centroid, the lowest of equals) and d2. No engine exchanges points.

    expr: generated code (or array lambdas for many coordinates); arrow: blocks and one matrix product; join: relational.
    """
    c = np.asarray(centroids, dtype=float)
    if engine == "expr":
        near = V.nearest_struct(F.col("x"), c) if c.size <= UNROLL_MAX else V.nearest_lambda(F.col("x"), F.array(*(V.vec(r) for r in c)))
        return df.withColumn("__n", near).select(*df.columns, F.col("__n.k").alias("k"), F.col("__n.d2").alias("d2"))
    if engine == "join":  # the inner side is K rows
        keyed = df.withColumn("__id", F.monotonically_increasing_id())
        both = keyed.crossJoin(F.broadcast(centroid_rows(df, c)))
        best = F.min_by(F.struct("k", V.sq_dist(F.col("x"), F.col("c")).alias("d2")), F.struct(V.sq_dist(F.col("x"), F.col("c")), "k")).alias("__n")
        firsts = [F.first(n).alias(n) for n in df.columns]
        return both.groupBy("__id").agg(*firsts, best).select(*df.columns, F.col("__n.k").alias("k"), F.col("__n.d2").alias("d2"))
    if engine != "arrow":
        raise ValueError(f"unknown engine {engine}")
    names, at = list(df.columns), df.columns.index("x")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            k, d2 = nearest(block(b.column(at), c.shape[1]), c)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(k, pa.int32()), pa.array(d2)], names=[*names, "k", "d2"])

    return df.mapInArrow(run, _with(df, "k int, d2 double"))


def _with(df: DataFrame, more: str):  # noqa: ANN202
    from pyspark.sql import types as T

    return T.StructType([*df.schema.fields, *T._parse_datatype_string(more).fields])


def assign_two(df: DataFrame, centroids: np.ndarray) -> DataFrame:
    """df with k1, k2 and margin, the gap between the two smallest squared distances."""
    c = np.asarray(centroids, dtype=float)
    names, at = list(df.columns), df.columns.index("x")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            one, two, gap = nearest_two(block(b.column(at), c.shape[1]), c)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(one, pa.int32()), pa.array(two, pa.int32()), pa.array(gap)], names=[*names, "k1", "k2", "margin"])

    return df.mapInArrow(run, _with(df, "k1 int, k2 int, margin double"))


_STATS = "model int, batch_seq long, k int, n double, sx array<double>, sxx double, sse double"


def partial_stats(df: DataFrame, models: Sequence[np.ndarray], weight_col: str | None = None) -> DataFrame:
    """One record per (model, batch, cluster) and task, for all models in one scan: what crosses the exchange never grows with points."""
    cs = [np.asarray(m, dtype=float) for m in models]
    d = cs[0].shape[1]
    cols = ["batch_seq", "x", *([weight_col] if weight_col else [])]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], Sums] = {}
        for b in batches:
            seq = b.column(0).to_numpy(zero_copy_only=False)
            x = block(b.column(1), d)
            w = b.column(2).to_numpy(zero_copy_only=False).astype(float) if weight_col else None
            for m, c in enumerate(cs):
                s = sums_of(x, seq, c, w)
                for i, q in enumerate(s.seqs.tolist()):
                    one = s.keep(np.arange(len(s.seqs)) == i)
                    if (old := held.get((m, q))) is None:
                        held[(m, q)] = one
                    else:
                        old.n += one.n
                        old.sx += one.sx
                        old.sxx += one.sxx
                        old.sse += one.sse
        rows = []
        for (m, q), s in held.items():
            for k in np.flatnonzero(s.n[0]).tolist():
                rows.append({"model": m, "batch_seq": q, "k": k, "n": s.n[0, k], "sx": s.sx[0, k].tolist(), "sxx": s.sxx[0, k], "sse": s.sse[0, k]})
        if rows:
            schema = pa.schema([("model", pa.int32()), ("batch_seq", pa.int64()), ("k", pa.int32()), ("n", pa.float64()), ("sx", pa.list_(pa.float64())), ("sxx", pa.float64()), ("sse", pa.float64())])
            yield pa.RecordBatch.from_pylist(rows, schema=schema)

    return df.select(*cols).mapInArrow(run, _STATS)


#: Coordinates of one model up to which a pass stays in generated code; beyond, blocks and a matrix product are faster.
EXPR_MAX = 40


def _expr_stats(df: DataFrame, c: np.ndarray, weight_col: str | None) -> DataFrame:
    w = F.col(weight_col).cast("double") if weight_col else F.lit(1.0)
    x = [F.col("x")[j] for j in range(c.shape[1])]
    near = V.nearest_struct(F.col("x"), c)
    rows = df.select("batch_seq", near.alias("near"), w.alias("w"), *(v.alias(f"x{j}") for j, v in enumerate(x)))
    weigh = (lambda e: e) if weight_col is None else (lambda e: F.col("w") * e)
    square = sum((F.col(f"x{j}") * F.col(f"x{j}") for j in range(1, len(x))), F.col("x0") * F.col("x0"))
    done = rows.groupBy("batch_seq", F.col("near.k").alias("k")).agg(
        F.sum("w").alias("n"), *(F.sum(weigh(F.col(f"x{j}"))).alias(f"s{j}") for j in range(len(x))), F.sum(weigh(square)).alias("sxx"), F.sum(weigh(F.col("near.d2"))).alias("sse")
    )
    return done.select(F.lit(0).alias("model"), "batch_seq", "k", "n", F.array(*(f"s{j}" for j in range(len(x)))).alias("sx"), "sxx", "sse")


def cluster_stats(df: DataFrame, models: Sequence[np.ndarray], weight_col: str | None = None, engine: str = "auto") -> DataFrame:
    """model, batch_seq, k, n, sx, sxx, sse: the materialised sums of a window under each model. engine: expr (one model), arrow, auto."""
    d = np.asarray(models[0]).shape[1]
    small = len(models) == 1 and np.asarray(models[0]).size <= EXPR_MAX
    if engine == "expr" or (engine == "auto" and small):
        return _expr_stats(df, np.asarray(models[0], dtype=float), weight_col)
    part = partial_stats(df, models, weight_col)
    sums = [F.sum(F.col("sx")[j]).alias(f"s{j}") for j in range(d)]
    done = part.groupBy("model", "batch_seq", "k").agg(F.sum("n").alias("n"), *sums, F.sum("sxx").alias("sxx"), F.sum("sse").alias("sse"))
    return done.select("model", "batch_seq", "k", "n", F.array(*(f"s{j}" for j in range(d))).alias("sx"), "sxx", "sse")


def gather(stats: DataFrame, n_models: int, k: Sequence[int], d: int) -> list[Sums]:
    """The few rows of cluster_stats or partial_stats as one Sums per model; parts of a cell add up."""
    t = stats.toArrow()
    model, seq, at = (t.column(c).to_numpy() for c in ("model", "batch_seq", "k"))
    n, sxx, sse = (t.column(c).to_numpy() for c in ("n", "sxx", "sse"))
    sx = np.asarray(t.column("sx").combine_chunks().flatten(), dtype=float).reshape(-1, d)
    seqs, place = np.unique(seq, return_inverse=True)
    out = []
    for m in range(n_models):
        s, mine = Sums.zeros(seqs, k[m], d), model == m
        cell = (place[mine], at[mine])
        for target, values in ((s.n, n), (s.sx, sx), (s.sxx, sxx), (s.sse, sse)):
            np.add.at(target, cell, values[mine])
        out.append(s)
    return out


def few_parts(df: DataFrame, cells: int, most: int = 200_000) -> bool:
    """Whether the tasks over df are few enough to send their sums straight to the driver, judged by the plan's size estimate."""
    spark = df.sparkSession
    size = float(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    tasks = max(size / (64 << 20), float(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    return tasks * cells <= most
