"""Scores of a run, all SQL over one fact table, and agreement with outside labels."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

MEASUREMENTS = "run_id string, dataset string, eps double, k int, m int, rho double, rep int, concept_id int, t_index int, batch_seq long, method string, metric string, value double"


def rel_excess(df: DataFrame, part: Sequence[str], methods: Sequence[str] | None = None) -> DataFrame:
    """score: relative excess over the best of the methods in the same part; null where the best is 0."""
    df = df if methods is None else df.where(F.col("method").isin(*methods))
    best = F.min("value").over(Window.partitionBy(*part))
    return df.withColumn("score", F.when(best != 0, (F.col("value") - best) / best))


def dist_ratio(df: DataFrame, part: Sequence[str], methods: Sequence[str] | None = None) -> DataFrame:
    """score: how many times the distances of the cheapest method."""
    df = df if methods is None else df.where(F.col("method").isin(*methods))
    best = F.min("value").over(Window.partitionBy(*part))
    return df.withColumn("score", F.when(best != 0, F.col("value") / best))


def boxplot_summary(df: DataFrame, by: Sequence[str], value: str = "score", exact: bool = True) -> DataFrame:
    """Quartiles, whiskers at 1.5 interquartile ranges (drawn to data), variance, outliers. exact False: percentile sketches."""
    q = (lambda p: F.percentile(value, F.lit(p))) if exact else (lambda p: F.percentile_approx(value, F.lit(p), F.lit(10_000)).cast("double"))
    box = df.where(F.col(value).isNotNull()).groupBy(*by).agg(q(0.25).alias("q1"), q(0.5).alias("med"), q(0.75).alias("q3"), F.var_samp(value).alias("variance"), F.count(F.lit(1)).alias("n"))
    lo, hi = F.col("q1") - 1.5 * (F.col("q3") - F.col("q1")), F.col("q3") + 1.5 * (F.col("q3") - F.col("q1"))
    joined = df.where(F.col(value).isNotNull()).join(F.broadcast(box), list(by))  # one row a box
    inside = F.col(value).between(lo, hi)
    return joined.groupBy(*by).agg(
        *(F.first(c).alias(c) for c in ("q1", "med", "q3", "variance", "n")),
        F.min(F.when(inside, F.col(value))).alias("lo_whisker"),
        F.max(F.when(inside, F.col(value))).alias("hi_whisker"),
        F.sum(F.when(inside, 0).otherwise(1)).alias("n_out"),
    )


def report(measurements: DataFrame, metric: str, methods: Sequence[str], by: Sequence[str] = ("t_index", "eps", "k", "method"), indices: Sequence[int] = (1, 2, 4, 10)) -> DataFrame:
    """One figure: box summaries of the normalised metric, pooled over datasets and repetitions."""
    part = ["run_id", "dataset", "eps", "k", "m", "rep", "batch_seq"]
    rows = measurements.where((F.col("metric") == metric) & F.col("t_index").isin(*indices))
    scored = (dist_ratio if metric == "distances" else rel_excess)(rows, part, methods)
    return boxplot_summary(scored, by)


def contingency(df: DataFrame, k: str, label: str) -> DataFrame:
    return df.groupBy(k, label).agg(F.count(F.lit(1)).alias("n"))


def purity(df: DataFrame, k: str, label: str) -> DataFrame:
    """value: share of points in their cluster's most frequent label."""
    c = contingency(df, k, label)
    return c.groupBy(k).agg(F.max("n").alias("m"), F.sum("n").alias("t")).agg((F.sum("m") / F.sum("t")).alias("value"))


def _margins(df: DataFrame, k: str, label: str) -> DataFrame:
    c = contingency(df, k, label)
    total = F.sum("n").over(Window.partitionBy(F.lit(0)))  # cells of the table, not points
    return c.select("n", F.sum("n").over(Window.partitionBy(k)).alias("a"), F.sum("n").over(Window.partitionBy(label)).alias("b"), total.alias("t"), F.col(k).alias("i"), F.col(label).alias("j"))


def adjusted_rand(df: DataFrame, k: str, label: str) -> DataFrame:
    """value: adjusted Rand index."""
    m = _margins(df, k, label)
    two = lambda c: c * (c - 1) / 2.0
    rows = m.agg(F.sum(two(F.col("n"))).alias("ij"), F.first("t").alias("t"))
    a = m.select("i", "a").distinct().agg(F.sum(two(F.col("a"))).alias("sa"))
    b = m.select("j", "b").distinct().agg(F.sum(two(F.col("b"))).alias("sb"))
    all_ = rows.crossJoin(F.broadcast(a)).crossJoin(F.broadcast(b))  # one row each
    expect = F.col("sa") * F.col("sb") / two(F.col("t"))
    top = (F.col("sa") + F.col("sb")) / 2.0
    return all_.select(F.when(top == expect, 1.0).otherwise((F.col("ij") - expect) / (top - expect)).alias("value"))


def normalised_mutual_information(df: DataFrame, k: str, label: str) -> DataFrame:
    """value: mutual information by the arithmetic mean of the entropies."""
    m = _margins(df, k, label)
    info = m.agg(F.sum(F.col("n") / F.col("t") * F.log(F.col("n") * F.col("t") / (F.col("a") * F.col("b")))).alias("mi"))
    h = lambda who, c: m.select(who, c, "t").distinct().agg((-F.sum(F.col(c) / F.col("t") * F.log(F.col(c) / F.col("t")))).alias(f"h{c}"))
    both = info.crossJoin(F.broadcast(h("i", "a"))).crossJoin(F.broadcast(h("j", "b")))
    mean = (F.col("ha") + F.col("hb")) / 2.0
    return both.select(F.when(mean == 0, 1.0).otherwise(F.col("mi") / mean).alias("value"))


def faded_running(df: DataFrame, order: str, value: str, rho: float, t_max: int, part: Sequence[str] = ()) -> DataFrame:
    """faded: the sum of rho^age * value over the last t_max rows, in one window."""
    w = (Window.partitionBy(*part) if part else Window.partitionBy(F.lit(0))).orderBy(order).rowsBetween(-(t_max - 1), 0)
    past = F.collect_list(F.col(value).cast("double")).over(w)
    return df.withColumn("faded", F.aggregate(past, F.lit(0.0), lambda s, v: s * F.lit(float(rho)) + v))


def farthest(df: DataFrame, m: int) -> DataFrame:
    """The m points of each cluster k that lie farthest from their centroid (needs k, d2, point_id)."""
    rank = F.row_number().over(Window.partitionBy("k").orderBy(F.desc("d2"), "point_id"))
    return df.withColumn("rank", rank).where(F.col("rank") <= m)


def distance_histogram(df: DataFrame, width: float) -> DataFrame:
    """k, bin, n: how distances to the centroid are spread; the largest squared distance is the bound u."""
    return df.groupBy("k", F.floor(F.sqrt("d2") / width).cast("long").alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.max("d2").alias("u"))
