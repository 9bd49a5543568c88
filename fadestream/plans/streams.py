"""Queries that drive streams over the given tables to their end, and the experiment reports."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fadestream.functions.kernels import Sums, nearest
from fadestream.operators import measures
from fadestream.operators.distance import block, cluster_stats
from fadestream.operators.engine import DriftOracleClusterer, FadingClusterer
from fadestream.operators.features import EIGHT, table
from fadestream.operators.forge import unit_directions
from fadestream.operators.lloyd import LocalWindow, lloyd
from fadestream.operators.seeding import local_kmpp
from fadestream.operators.starts import BlendSeed
from fadestream.plans import duck as Q
from fadestream.plans.experiments import gap_experiment, rho_tradeoff, run_grid
from fadestream.plans.methods import EV5, D, K, ev, fifths, first_rows, r6
from fadestream.plans.operations import scratch
from fadestream.plans.registry import query, rounded
from fadestream.sources import datasources
from fadestream.sources.window_store import WindowStore
from fadestream.streaming import fit

_EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def _files(spark: SparkSession, df: DataFrame, by: str, label: str) -> str:
    """The rows as one file per value of `by`, in order of arrival."""
    path = scratch(spark, label)
    for v in [r[0] for r in df.select(by).distinct().orderBy(by).collect()]:
        df.where(F.col(by) == v).drop(by).coalesce(1).write.mode("append").parquet(path)
    return path


def _drain(df: DataFrame, sink: str, mode: str, label: str, spark: SparkSession) -> DataFrame:
    name = f"{label}_{uuid.uuid4().hex}"
    out = scratch(spark, name)
    if sink == "memory":
        q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", f"{out}-cp").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.table(name)
    q = df.writeStream.outputMode(mode).format("parquet").option("path", out).option("checkpointLocation", f"{out}-cp").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


@query(f"WITH {EV5}, {Q.first_rows('c0', 'ev5', K, D)}, {Q.near('a', 'ev5', 'c0', D)} SELECT b, CAST(k AS INTEGER) AS k, count(*) AS n FROM a GROUP BY b, k")
def stream_count_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Micro-batches of one file each through foreachBatch; each writes its sums under its own number, twice, to the same effect."""
    p = fifths(spark, sf_dir).withColumn("b", F.col("batch_seq")).persist()
    c = first_rows(p)
    path, out = _files(spark, p.select("point_id", "x", "b"), "b", "count"), scratch(spark, "count-out")

    def step(batch: DataFrame, epoch: int) -> None:
        stats = cluster_stats(batch.withColumn("batch_seq", F.lit(epoch).cast("long")), [c]).select("k", F.col("n").cast("long").alias("n"))
        for _ in range(2):
            stats.coalesce(1).write.mode("overwrite").parquet(f"{out}/b={epoch}")

    stream = fit.file_stream(spark, path, "point_id string, x array<double>")
    stream.writeStream.foreachBatch(step).option("checkpointLocation", f"{out}-cp").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("k int, n long, b long").parquet(out).select("b", "k", "n")


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = spark.readStream.schema(_EVENTS).parquet(f"{sf_dir}/events.parquet*").withColumn("t", F.col("ts").cast("timestamp"))
    agg = e.withWatermark("t", "1 day").groupBy(F.window("t", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    out = _drain(agg, "memory", "complete", "tumbling", spark)
    return out.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query("SELECT DISTINCT event_id AS id FROM events")
def stream_dedup_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select("event_id", "ts")
    path = _files(spark, e.withColumn("b", F.lit(0)).unionByName(e.where("event_id % 4 = 0").withColumn("b", F.lit(1))), "b", "dedup")
    stream = fit.file_stream(spark, path, "event_id long, ts timestamp_ntz")
    return _drain(fit.deduplicated(stream, "ts", "event_id", "3650 days"), "parquet", "append", "dedup", spark).select(F.col("event_id").alias("id"))


@query(f"WITH {EV5}, f AS (SELECT user_id % 3 AS u, b, count(*) AS n FROM ev5 JOIN events ON id = event_id GROUP BY 1, 2) SELECT CAST(u AS VARCHAR) AS key, b AS batch_seq, CAST(sum(n) OVER (PARTITION BY u ORDER BY b ROWS BETWEEN 1 PRECEDING AND CURRENT ROW) AS BIGINT) AS n FROM f")
def stream_keyed_state_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A fading model a key with two retained batches: the points each model was fitted to."""
    u = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), (F.col("user_id") % 3).alias("u"))
    p = fifths(spark, sf_dir).join(u, "id").select("u", "x", F.col("batch_seq").alias("b")).persist()
    stream = fit.file_stream(spark, _files(spark, p, "b", "keyed"), "u long, x array<double>")
    out = _drain(fit.fit_keyed(stream, "u", 3, 0.5, 2), "parquet", "append", "keyed", spark)
    return out.groupBy("key", "batch_seq").agg(F.sum("n").alias("n"))


@query("WITH e AS (SELECT event_id, CAST(floor(epoch(ts) / 86400) AS BIGINT) AS d, event_id % 10 = 0 AS held FROM events), m AS (SELECT max(d) AS top FROM e WHERE NOT held) SELECT event_id AS id, CASE WHEN held AND d <= top - 3 THEN 'late' ELSE 'kept' END AS route, d AS batch_seq FROM e, m")
def stream_late_routed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every tenth event arrives after the rest: those of retained days join their own day, older ones go to the late sink."""
    e = table(spark, sf_dir, "events").select("event_id", "ts")
    path = _files(spark, e.withColumn("b", (F.col("event_id") % 10 == 0).cast("int")), "b", "late")
    kept, late = scratch(spark, "kept"), scratch(spark, "late")
    keep = lambda to: lambda df, epoch: df.select("event_id", "batch_seq").write.mode("overwrite").parquet(f"{to}/e={epoch}")
    fit.fit_event_time(fit.file_stream(spark, path, "event_id long, ts timestamp_ntz"), "ts", 86_400, 3, keep(kept), keep(late), f"{kept}-cp").awaitTermination()
    read = lambda p, r: spark.read.schema("event_id long, batch_seq long, e int").parquet(p).select(F.col("event_id").alias("id"), F.lit(r).alias("route"), "batch_seq")
    return read(kept, "kept").unionByName(read(late, "late"))


@query(f"WITH {EV5}, {Q.first_rows('c0', 'ev5', K, D)}, {Q.near('a', 'ev5', 'c0', D)} SELECT id, CAST(k AS INTEGER) AS k, CAST(d2 AS BIGINT) AS d2 FROM a")
def stream_scored_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = fifths(spark, sf_dir).withColumn("b", F.col("batch_seq")).persist()
    stream = fit.file_stream(spark, _files(spark, p.select("id", "x", "b"), "b", "scored"), "id long, x array<double>")
    out = _drain(fit.score_stream(stream, first_rows(p)), "parquet", "append", "scored", spark)
    return out.select("id", "k", F.col("d2").cast("long").alias("d2"))


@query("SELECT event_id AS id, event_type AS label FROM events")
def stream_stream_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels that come an hour after their events, joined within three hours."""
    e = table(spark, sf_dir, "events")
    a = _files(spark, e.select("event_id", "ts", F.lit(0).alias("b")), "b", "ss-events")
    lab = e.select(F.col("event_id"), (F.col("ts").cast("timestamp") + F.expr("INTERVAL 1 HOUR")).alias("lts"), F.col("event_type").alias("label"), F.lit(0).alias("b"))
    b = _files(spark, lab, "b", "ss-labels")
    joined = fit.with_late_labels(fit.file_stream(spark, a, "event_id long, ts timestamp_ntz"), fit.file_stream(spark, b, "event_id long, lts timestamp, label string"), "event_id", "ts", "lts", "3 HOURS")
    return _drain(joined, "parquet", "append", "ss", spark).select(F.col("event_id").alias("id"), "label")


def _fitted_stream(spark: SparkSession, sf_dir: str, start: str) -> DataFrame:
    p = fifths(spark, sf_dir).withColumn("b", F.col("batch_seq")).persist()
    stream = fit.file_stream(spark, _files(spark, p.select("point_id", "x", "b"), "b", "fit"), "point_id string, x array<double>")
    store = WindowStore(spark, scratch(spark, "fit-store"))
    rows: list[tuple] = []
    f = FadingClusterer(K, 0.5, 3, start, store=store, max_iter=20)
    fit.fit_stream(stream, f, f"{store.root}-cp", lambda r: rows.append((r.seq, r.init_faded, r.final_faded, r.iterations, r.total_distances))).awaitTermination()
    return spark.createDataFrame(rows, "batch_seq long, init_error double, final_error double, iterations int, distances long")


query(None, "stream_fit_pair")(lambda s, d: _fitted_stream(s, d, "pair"))


def forged_events(spark: SparkSession, sf_dir: str, k: int, period: int, eps: float) -> DataFrame:
    """id, batch_seq, x: the batches of events, whose clusters (those of the first batch) jump by sqrt(eps) spreads every `period` batches."""
    p = ev(spark, sf_dir).select("id", "batch_seq", "x")
    first = p.where(F.col("batch_seq") == p.agg(F.min("batch_seq")).first()[0]).orderBy("id").toArrow()  # one batch
    x = block(first.column("x").combine_chunks(), D)
    c = lloyd(LocalWindow(x, np.zeros(len(x), dtype=np.int64)), local_kmpp(x, k, np.random.default_rng(0))).centroids
    step = float(np.sqrt(eps * nearest(x, c)[1].mean() / 2.0))  # two independent moves are sqrt(2) steps apart

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, concept = block(b.column(2), D), b.column(1).to_numpy() // period
            k_of, moved = nearest(x, c)[0], x.copy()
            for i in np.unique(concept[concept > 0]).tolist():
                at = concept == i
                moved[at] += step * unit_directions(k, D, i)[k_of[at]]
            flat = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * D), pa.array(moved.ravel()))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), flat], names=["id", "batch_seq", "x"])

    return p.mapInArrow(run, "id long, batch_seq long, x array<double>")


@query(None)
def source_drift_forge(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stream of forged drifts by batch, made of events."""
    df = forged_events(spark, sf_dir, k=4, period=3, eps=1.0)
    return df.groupBy("batch_seq").agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("x")[0]).alias("mean"))


@query("SELECT event_id // 2000 AS batch_seq, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
def source_ordinal_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events written in order to one file, then replayed in batches of exactly 2000 by the Python source as a stream."""
    datasources.register(spark)
    path = scratch(spark, "replay").removeprefix("file://")
    table(spark, sf_dir, "events").select("event_id", "value").orderBy("event_id").coalesce(1).write.parquet(path)
    stream = spark.readStream.format("ordinal_replay").options(path=path, columns="value", n="2000").load()
    rows: list[tuple] = []

    def step(batch: DataFrame, epoch: int) -> None:
        rows.extend(tuple(r) for r in batch.groupBy("batch_seq").agg(F.count(F.lit(1)), F.sum(F.col("x")[0])).collect())

    q = stream.writeStream.foreachBatch(step).option("checkpointLocation", scratch(spark, "replay-cp")).start()
    q.processAllAvailable()
    q.stop()
    return spark.createDataFrame([(int(b), int(n), rounded(float(t), 4)) for b, n, t in rows], "batch_seq long, n long, total double")


@query("SELECT event_id % 5 AS k, count(*) AS count FROM events GROUP BY 1")
def source_rate_demo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream, counted by a remainder of their number."""
    e = spark.readStream.schema(_EVENTS).parquet(f"{sf_dir}/events.parquet*")
    return _drain(e.groupBy((F.col("event_id") % 5).alias("k")).count(), "memory", "complete", "rate", spark)


# ---------------------------------------------------------------- the figures over a run that SQL replays

#: Batches after the first of the replayed run; batches of its window; the policies whose scores are compared.
STEPS, KEEP = 10, 3
RUN_METHODS = ["carry", "fresh", "blend", "pair"]
FACTS = "run_id string, dataset string, eps double, k int, m int, rep int, batch_seq long, t_index int, method string, metric string, value double"


def run_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Facts of real steps on the events: every policy starts from the same previous centroids (those of pair) and the same seeds (the
    batch's first points), and makes one update; the reference is told of a change at batch 1. No randomness, so SQL can replay it."""
    p = ev(spark, sf_dir).where(F.col("batch_seq") <= STEPS).persist()
    rows = p.select("id", "batch_seq", "x").orderBy("id").collect()  # a few batches of a few points
    x, seq = np.array([r["x"] for r in rows]), np.array([r["batch_seq"] for r in rows])
    policies = {n: BlendSeed("past", max_iter=1) if n == "blend" else n for n in RUN_METHODS}
    fades = {n: FadingClusterer(K, 0.5, KEEP, q, max_iter=1) for n, q in policies.items()}
    oracle, shared, out = DriftOracleClusterer(K, max_iter=1), None, []
    for s in range(STEPS + 1):
        batch = x[seq == s]
        if not len(batch):
            break
        seeds = batch[:K]
        given = (*shared, seeds) if shared else (seeds, Sums.zeros([], K, D), seeds)
        done = {n: f.step(batch, s, given) for n, f in fades.items()}
        done["reference"] = oracle.step(batch, s == 1, s, seeds)
        lead = done["pair" if s else "carry"]
        shared = (lead.centroids, lead.sums)
        for n, r in done.items() if s else ():
            values = {"since_drift": r.since_drift(1), "distances": float(r.total_distances)}
            if n != "reference":
                values |= {"init_faded": r.init_faded, "final_faded": r.final_faded}
            out += [("replay", "events", 0.0, K, 0, 0, s, s, n, metric, float(v)) for metric, v in values.items()]
    return spark.createDataFrame(out, FACTS)


def _run_sql() -> str:
    """CTE vals (b, method, metric, v): the same run, step by step."""
    parts, now = [Q.EV, Q.first_rows("c_0", "ev", K, D), "w_0 AS (SELECT * FROM ev WHERE b = 0)"], "c_0"
    body, now = Q.lloyd("z_", "w_0", now, 1, D, "pow(0.5, 0 - a.b)")
    parts.append(body)
    told, values = "", []
    cols = lambda p: ", ".join(f"{p}.c{j}" for j in range(1, D + 1))
    for s in range(1, STEPS + 1):
        lo, faded = max(0, s - KEEP + 1), f"pow(0.5, {s} - a.b)"
        parts += [f"w_{s} AS (SELECT * FROM ev WHERE b BETWEEN {lo} AND {s})", f"o_{s} AS (SELECT * FROM ev WHERE b BETWEEN {lo} AND {s - 1})", f"n_{s} AS (SELECT * FROM ev WHERE b = {s})"]
        parts += [Q.near(f"pa_{s}", f"o_{s}", now, D), f"past_{s} AS (SELECT c.*, coalesce(w, 0) AS w FROM {now} c LEFT JOIN (SELECT k, sum(pow(0.5, {s} - b)) AS w FROM pa_{s} GROUP BY k) USING (k))"]
        parts += [Q.first_rows(f"s_{s}", "ev", K, D, f"b = {s}"), Q.near(f"fa_{s}", f"n_{s}", f"s_{s}", D), f"fresh_{s} AS (SELECT c.*, coalesce(w, 0) AS w FROM s_{s} c LEFT JOIN (SELECT k, CAST(count(*) AS DOUBLE) AS w FROM fa_{s} GROUP BY k) USING (k))"]
        gap = Q.d2("p", "f", D, "c", "c")
        parts.append(f"cost_{s} AS (SELECT p.k AS i, f.k AS j, CASE WHEN p.w + f.w > 0 THEN p.w * f.w / (p.w + f.w) * ({gap}) ELSE 0 END AS cost FROM past_{s} p CROSS JOIN fresh_{s} f)")
        names, distinct = "abcd"[:K], " AND ".join(f"{x}.j <> {y}.j" for i, x in enumerate("abcd"[:K]) for y in "abcd"[i + 1 : K])
        parts.append(f"perm_{s} AS (SELECT {', '.join(f'{x}.j AS j{i}' for i, x in enumerate(names))}, {' + '.join(f'{x}.cost' for x in names)} AS total FROM {', '.join(f'cost_{s} {x}' for x in names)} WHERE {' AND '.join(f'{x}.i = {i}' for i, x in enumerate(names))} AND {distinct} ORDER BY total LIMIT 1)")
        parts.append(f"sigma_{s} AS ({' UNION ALL '.join(f'SELECT {i} AS i, j{i} AS j FROM perm_{s}' for i in range(K))})")
        merged = ", ".join(f"CASE WHEN p.w + f.w > 0 THEN (p.w * p.c{j} + f.w * f.c{j}) / (p.w + f.w) ELSE p.c{j} END AS c{j}" for j in range(1, D + 1))
        parts.append(f"pair_{s} AS (SELECT p.k, {merged} FROM past_{s} p JOIN sigma_{s} g ON p.k = g.i JOIN fresh_{s} f ON f.k = g.j)")
        point = ", ".join(f"c{j} AS v{j}" for j in range(1, D + 1))
        parts.append(f"pts_{s} AS (SELECT k AS id, CAST(0 AS BIGINT) AS b, {point}, w FROM past_{s} WHERE w > 0 UNION ALL SELECT k + 100, CAST(0 AS BIGINT), {point}, w FROM fresh_{s} WHERE w > 0)")
        inner, blend = Q.lloyd(f"i_{s}_", f"pts_{s}", f"past_{s}", 1, D, "a.w")
        parts.append(inner)
        new, all_ = f"(SELECT count(*) FROM n_{s})", f"(SELECT count(*) FROM w_{s})"
        extra = {"carry": "0", "fresh": f"{new} * {K}", "blend": f"{new} * {K} + (SELECT count(*) FROM pts_{s}) * {2 * K}", "pair": f"{new} * {K} + {K * K}"}
        for m, start in (("carry", f"past_{s}"), ("fresh", f"fresh_{s}"), ("blend", blend), ("pair", f"pair_{s}")):
            parts.append(f"t_{m}_{s} AS (SELECT k, {cols(start)} FROM {start})")
            body, last = Q.lloyd(f"{m}_{s}_", f"w_{s}", f"t_{m}_{s}", 1, D, faded)
            parts += [body, Q.near(f"{m}_{s}_z", f"w_{s}", last, D)]
            mean = f"sum(pow(0.5, {s} - b) * d2) / sum(pow(0.5, {s} - b))"
            values += [f"SELECT {s} AS b, '{m}' AS method, 'init_faded' AS metric, {mean} AS v FROM {m}_{s}_a1", f"SELECT {s}, '{m}', 'final_faded', {mean} FROM {m}_{s}_z"]
            values += [f"SELECT {s}, '{m}', 'since_drift', avg(d2) FROM {m}_{s}_z WHERE b >= 1", f"SELECT {s}, '{m}', 'distances', CAST(2 * {K} * {all_} + {extra[m]} AS DOUBLE)"]
        now = last
        told = told or f"s_{s}"
        parts.append(f"d_{s} AS (SELECT * FROM ev WHERE b BETWEEN 1 AND {s})")
        body, told = Q.lloyd(f"r_{s}_", f"d_{s}", told, 1, D)
        parts += [body, Q.near(f"r_{s}_z", f"d_{s}", told, D)]
        values += [f"SELECT {s}, 'reference', 'since_drift', avg(d2) FROM r_{s}_z", f"SELECT {s}, 'reference', 'distances', CAST(2 * {K} * (SELECT count(*) FROM d_{s}) + {f'{new} * {K}' if s == 1 else 0} AS DOUBLE)"]
    parts.append("every AS (" + " UNION ALL ".join(values) + "), vals AS (SELECT * FROM every WHERE b <= (SELECT max(b) FROM ev))")
    return ",\n".join(parts)


_RUN = _run_sql()


@query(Q.with_(_RUN, select="SELECT CAST(b AS BIGINT) AS batch_seq, method, metric, round(v, 5) AS value FROM vals"))
def fading_run_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return run_facts(spark, sf_dir).select("batch_seq", "method", "metric", F.round("value", 5).alias("value"))


def _report(metric: str):  # noqa: ANN202
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        who = RUN_METHODS + (["reference"] if metric == "since_drift" else [])
        box = measures.report(run_facts(spark, sf_dir), metric, who, ("method",))
        return box.select("method", *(F.round(c, 5).alias(c) for c in ("med", "q1", "q3")), "n")

    return run


for _name, _metric in {"initial": "init_faded", "converged": "final_faded", "since_drift": "since_drift", "distances": "distances"}.items():
    _norm = "v / min(v) OVER (PARTITION BY b)" if _name == "distances" else "(v - min(v) OVER (PARTITION BY b)) / min(v) OVER (PARTITION BY b)"
    _who = "" if _name == "since_drift" else "AND method <> 'reference'"
    query(
        Q.with_(
            _RUN, f"sc AS (SELECT method, {_norm} AS s FROM vals WHERE metric = '{_metric}' AND b IN (1, 2, 4, 10) {_who})",
            select="SELECT method, round(quantile_cont(s, 0.5), 5) AS med, round(quantile_cont(s, 0.25), 5) AS q1, round(quantile_cont(s, 0.75), 5) AS q3, count(*) AS n FROM sc GROUP BY 1",
        ),
        f"report_{_name}",
    )(_report(_metric))


@query(Q.with_(_RUN, select="SELECT CAST(b AS BIGINT) AS batch_seq, method, v AS distances, round(v / min(v) OVER (PARTITION BY b), 6) AS ratio FROM vals WHERE metric = 'distances' AND method <> 'reference'"))
def dist_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distances that each policy's steps took, against the stated costs, and their ratio to the cheapest."""
    rows = run_facts(spark, sf_dir).where("metric = 'distances'")
    return measures.dist_ratio(rows, ["batch_seq"], RUN_METHODS).select("batch_seq", "method", F.col("value").alias("distances"), r6("score").alias("ratio"))


# ---------------------------------------------------------------- the experiments at small size


def _grid(spark: SparkSession, sf_dir: str, **options) -> DataFrame:  # noqa: ANN003
    """The fact table of a grid, written once: its summaries read it more than once."""
    facts = run_grid(spark, sf_dir, options.pop("datasets", ["lineitem2", "embed50"]), **({"n": 100, "concepts": 3, "eps": (1.0,), "ks": (5,)} | options))
    path = scratch(spark, f"grid_{uuid.uuid4().hex}")
    facts.write.parquet(path)
    return spark.read.schema(facts.schema).parquet(path)


def _summary(facts_: DataFrame, by: tuple[str, ...] = ("metric", "t_index", "method")) -> DataFrame:
    """Box summaries of relative excesses over the best; of distances, ratios to the cheapest start policy (the reference has another window)."""
    part = Window.partitionBy("run_id", "dataset", "eps", "k", "m", "rep", "batch_seq", "metric", *(["t_max"] if "t_max" in by else []))
    rows = facts_.where(F.col("t_index").isin(1, 2, 4, 10) & ((F.col("metric") != "distances") | (F.col("method") != "reference")))
    best = F.min("value").over(part)
    score = F.when(F.col("metric") == "distances", F.col("value") / best).otherwise((F.col("value") - best) / best)
    return measures.boxplot_summary(rows.withColumn("score", F.when(best != 0, score)), by)


query(None, "grid_small")(lambda s, d: _summary(_grid(s, d)))
query(None, "grid_eight_sets")(lambda s, d: _summary(_grid(s, d, datasets=EIGHT, concepts=2)))
query(None, "grid_m_sweep")(lambda s, d: _summary(_grid(s, d, datasets=["lineitem2"], ms=(1, 2, 4)), ("m", "metric", "t_index", "method")))
query(None, "grid_refined_starts")(lambda s, d: _summary(_grid(s, d, datasets=["lineitem2"], c0_refine="mean", recenter_past=True)))
query(None, "grid_independent")(lambda s, d: _summary(_grid(s, d, datasets=["lineitem2"], shared_from="independent")))
query(None, "grid_truncation")(lambda s, d: _summary(_grid(s, d, datasets=["lineitem2"], t_maxes=(2, 6, 12)), ("t_max", "metric", "t_index", "method")))
query(None, "gap_experiment_a")(lambda s, d: gap_experiment(s, d, rho=0.676, n=1000))
query(None, "gap_experiment_b")(lambda s, d: gap_experiment(s, d, rho=0.676, n=4000))
query(None, "gap_experiment_c")(lambda s, d: gap_experiment(s, d, rho=0.822, n=1000))


@query(None)
def gap_bias_variance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean and variance of the measured gaps by forget parameter and age of the drift: small rho is off for fewer batches and varies more."""
    gaps = None
    for rho in (0.457, 0.676, 0.822):
        one = gap_experiment(spark, sf_dir, rho=rho, n=1000, deltas=(0.05,)).select(F.lit(rho).alias("rho"), "t", "gap")
        gaps = one if gaps is None else gaps.unionByName(one)
    return rho_tradeoff(gaps)


def _stated(k: int):  # noqa: ANN202
    """The experiment as stated, for one number of clusters: three strengths of drift, eight sets, batches of 500, ten drifts of ten batches after the burn-in."""
    return lambda s, d: _summary(_grid(s, d, datasets=EIGHT, eps=(0.5, 1.0, 2.0), ks=(k,), n=500, concepts=10), ("eps", "k", "metric", "t_index", "method"))


for _k in (5, 10, 25):
    query(None, f"grid_full_k{_k}")(_stated(_k))


@query(None)
def drift_picture(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two clusters in two dimensions before and after a move: means of each cluster."""
    from fadestream.operators.features import lineitem2, zscore
    from fadestream.operators.forge import DriftForge

    block = zscore(lineitem2(spark, sf_dir), 2).select("point_id", "x").withColumn("batch_seq", F.lit(0).cast("long")).persist()
    f = DriftForge(1.0, 2, 3, mode="grid").next(block)
    rows = [(k, c.tolist(), (c + f.magnitude.alpha * x).tolist(), f.magnitude.ratio) for k, (c, x) in enumerate(zip(f.centroids, f.xi, strict=True))]
    return spark.createDataFrame(rows, "k int, before array<double>, after array<double>, ratio double")


@query(None)
def detector_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The reference under false alarms and misses of its signal, over drifts forged in events; stretches between signals run side by side."""
    from fadestream.operators.engine import corrupt_signal

    period = 5
    p = forged_events(spark, sf_dir, k=4, period=period, eps=4.0)
    truth = [s > 0 and s % period == 0 for s in range(ev(spark, sf_dir).agg(F.max("batch_seq")).first()[0] + 1)]
    signals = []
    for p_false, p_miss in ((0.0, 0.0), (0.3, 0.0), (0.0, 0.5), (0.3, 0.5)):
        stretch = np.cumsum(corrupt_signal(truth, p_false, p_miss, 1))
        signals += [(p_false, p_miss, s, int(n)) for s, n in enumerate(stretch)]

    def run(f: pd.DataFrame) -> pd.DataFrame:
        oracle, rows = DriftOracleClusterer(4, max_iter=50), []
        for s, batch in f.sort_values(["batch_seq", "id"]).groupby("batch_seq"):
            r = oracle.step(np.stack(batch["x"]), not rows, int(s))
            rows.append((f["p_false"].iloc[0], f["p_miss"].iloc[0], s, r.since_drift(s - s % period)))
        return pd.DataFrame(rows, columns=["p_false", "p_miss", "batch_seq", "error"])

    told = spark.createDataFrame(signals, "p_false double, p_miss double, batch_seq long, stretch long")
    out = p.join(told, "batch_seq").groupBy("p_false", "p_miss", "stretch").applyInPandas(run, "p_false double, p_miss double, batch_seq long, error double")
    return out.groupBy("p_false", "p_miss").agg(F.avg("error").alias("error"))
