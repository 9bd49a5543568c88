"""The clusterers on DataFrames against the array reference, stores and recovery, drifts, experiments, streams, plans, oracle."""

import datetime
import math
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from fadestream.functions.kernels import fading, nearest, sums_of
from fadestream.operators import batching, features
from fadestream.operators.distance import assign, cluster_stats
from fadestream.operators.engine import DriftOracleClusterer, FadingClusterer, bound_slack, clusterer, corrupt_signal
from fadestream.operators.estimator import FadingKMeans, FadingKMeansModel
from fadestream.operators.forge import DriftForge, search_alpha, unit_directions
from fadestream.operators.kchoice import silhouette
from fadestream.operators.lloyd import GrowingWindow, LocalWindow, SparkWindow, lloyd
from fadestream.operators.measures import boxplot_summary, rel_excess
from fadestream.operators.seeding import HeldPoints, held_kmpp, local_uniform, seed_forgy, seed_kmpp, seed_mcmc, seed_parallel
from fadestream.plans import catalogue, methods
from fadestream.plans.experiments import gap_experiment, run_grid
from fadestream.sources.window_store import WindowStore
from fadestream.streaming import fit


def batches(n=12, size=120, k=3, d=2, drift=6, seed=0):
    rng = np.random.default_rng(seed)
    out, centres = [], rng.normal(scale=8, size=(k, d))
    for i in range(n):
        if i and i % drift == 0:
            centres = centres + rng.normal(scale=3, size=(k, d))
        out.append(centres[rng.integers(0, k, size)] + rng.normal(size=(size, d)))
    return out


def frame(spark, x, seq=0):
    return spark.createDataFrame([(str(i), v, seq) for i, v in enumerate(x.tolist())], "point_id string, x array<double>, batch_seq long").repartition(3)


@pytest.mark.parametrize("start", ["carry", "fresh", "blend", "pair"])
def test_distributed_steps_equal_the_reference(spark, tmp_path, start):
    data = batches(7)
    local = FadingClusterer(3, 0.5, 4, start, seed=1)
    store = WindowStore(spark, str(tmp_path / "w"))
    far = FadingClusterer(3, 0.5, 4, start, seed=1, store=store)
    far._seeds = lambda newest: local._seeds(LocalWindow(data[far.seq], np.zeros(len(data[far.seq]))))
    for i, x in enumerate(data):
        a, b = local.step(x), far.step(frame(spark, x), i)
        assert np.allclose(a.centroids, b.centroids) and math.isclose(a.final_faded, b.final_faded, rel_tol=1e-9)
        assert a.distances == b.distances and a.iterations == b.iterations
        assert a.sums.seqs.tolist() == b.sums.seqs.tolist() == list(range(max(0, i - 3), i + 1))
    assert store.batches() == [3, 4, 5, 6]


def test_weights_add_up_to_the_mass():
    f = FadingClusterer(3, 0.6, 4, "pair")
    for x in batches(8, size=50):
        r = f.step(x)
        if r.past is not None:
            assert math.isclose(r.past.w.sum() + r.fresh.w.sum(), r.mass)


def test_resume_equals_an_uninterrupted_run(spark, tmp_path):
    data = [frame(spark, x) for x in batches(5)]
    whole = FadingClusterer(3, 0.5, 3, "carry", store=WindowStore(spark, str(tmp_path / "a")))
    ends = [whole.step(x, i).centroids for i, x in enumerate(data)]
    root = str(tmp_path / "b")
    first = FadingClusterer(3, 0.5, 3, "carry", store=WindowStore(spark, root))
    for i in range(3):
        first.step(data[i], i)
    again = FadingClusterer(3, 0.5, 3, "carry", store=WindowStore(spark, root))
    assert again.resume() == 2
    for i in (3, 4):
        assert np.allclose(again.step(data[i], i).centroids, ends[i])


def test_reference_equals_fading_without_fading():
    data = batches(9, drift=99)
    oracle, static = DriftOracleClusterer(3, seed=2), FadingClusterer(3, 1.0, None, "carry", seed=2)
    for i, x in enumerate(data):
        a, b = oracle.step(x, i == 0), static.step(x)
        assert np.allclose(a.centroids, b.centroids) and math.isclose(a.final_faded, b.final_faded)
        assert math.isclose(b.since_drift(0), b.final_faded)
    reset = clusterer("reset", 3)
    reset.step(data[0], True)
    reset.step(data[1], True)
    assert reset.sums.seqs.tolist() == [1]
    assert clusterer("newest", 3).t_max == 1 and clusterer("static", 3).t_max is None
    capped = DriftOracleClusterer(3, max_batches=2)
    for i, x in enumerate(data):
        capped.step(x, False)
    assert len(capped.sums.seqs) == 2


def test_corrupt_signal():
    truth = [i % 5 == 0 for i in range(1000)]
    assert corrupt_signal(truth, 0, 0) == truth
    got = corrupt_signal(truth, 0.1, 0.5, 3)
    assert 60 < sum(t and g for t, g in zip(truth, got, strict=True)) < 140 and 40 < sum(g and not t for t, g in zip(truth, got, strict=True)) < 120


def test_engines_agree_and_do_not_exchange(spark):
    x = np.random.default_rng(1).normal(size=(500, 3))
    df, c = frame(spark, x), x[:4]
    k, d2 = nearest(x, c)
    for engine in ("expr", "arrow", "join"):
        rows = {int(r["point_id"]): r for r in assign(df, c, engine).collect()}
        assert all(rows[i]["k"] == k[i] and math.isclose(rows[i]["d2"], d2[i], abs_tol=1e-9) for i in range(500))
    base = spark.range(10).select(F.array(F.col("id") * 1.0).alias("x"), F.lit(0).cast("long").alias("batch_seq"))
    for engine in ("expr", "arrow"):
        plan = assign(base, np.array([[0.0], [5.0]]), engine)._jdf.queryExecution().executedPlan().toString()
        assert "Exchange" not in plan and "NestedLoop" not in plan and "Cartesian" not in plan


def test_window_reads_prune_partitions(spark, tmp_path):
    store = WindowStore(spark, str(tmp_path / "w"))
    for s in range(4):
        store.append(frame(spark, np.ones((3, 2)) * s), s)
    plan = store.window(2, 3)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(batch_seq" in plan
    assert store.window(2, 3).count() == 6
    store.append(frame(spark, np.ones((3, 2))), 3)
    assert store.window(3, 3).count() == 3


def test_one_scan_for_many_models(spark):
    df = frame(spark, np.random.default_rng(1).normal(size=(100, 2)))
    plan = cluster_stats(df, [np.zeros((2, 2)), np.ones((3, 2)), np.ones((1, 2))])._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == 1
    w = df.withColumn("w", F.col("point_id").cast("double") % 3)
    for col in (None, "w"):
        a, b = ({(r["batch_seq"], r["k"]): r for r in cluster_stats(w, [np.eye(2)], col, e).collect()} for e in ("expr", "arrow"))
        assert a.keys() == b.keys()
        assert all(np.allclose([a[q][c] for c in ("n", "sxx", "sse")], [b[q][c] for c in ("n", "sxx", "sse")]) and np.allclose(a[q]["sx"], b[q]["sx"]) for q in a)
    for d in (1, 3, 7):
        x = np.random.default_rng(d).normal(size=(50, d))
        for direct in (True, False):
            s = SparkWindow(frame(spark, x), direct=direct).passes([x[:2]])[0]
            assert np.allclose(s.n, LocalWindow(x, np.zeros(50, dtype=int)).passes([x[:2]])[0].n)
        assert np.allclose(s.sx, LocalWindow(x, np.zeros(50, dtype=int)).passes([x[:2]])[0].sx)


def test_spark_seedings(spark):
    x = np.concatenate([np.random.default_rng(i).normal(size=(60, 2)) + 20 * i for i in range(4)])
    df = frame(spark, x).persist()
    for seeds in (seed_kmpp(df, 4), seed_parallel(df, 4), seed_mcmc(df, 4, 60), seed_mcmc(df, 4, 60, proposal="distance")):
        assert len({int(round(c[0] / 20)) for c in seeds}) == 4
    assert seed_forgy(df, 4).shape == (4, 2)
    assert np.array_equal(seed_kmpp(df, 4, 3), seed_kmpp(df.repartition(7), 4, 3))
    assert len(seed_kmpp(frame(spark, np.ones((5, 2))), 3)) == 3
    u = df.select(F.col("point_id"), __import__("fadestream.operators.seeding", fromlist=["_u"])._u(4, 1).alias("u")).limit(5).collect()
    assert all(math.isclose(r["u"], local_uniform(r["point_id"], 4, 1)) for r in u)


def test_passes_match_the_library_clusterer(spark):
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    x = np.concatenate([np.random.default_rng(i).normal(size=(80, 2)) + 15 * i for i in range(3)])
    df = frame(spark, x)
    ours = lloyd(SparkWindow(df), seed_kmpp(df, 3)).errors[-1]
    theirs = KMeans(k=3, seed=1).fit(df.select(array_to_vector("x").alias("features"))).summary.trainingCost / len(x)
    assert math.isclose(ours, theirs, rel_tol=1e-6)


@pytest.mark.parametrize("mode", ["step", "grid"])
def test_forged_drift(spark, mode):
    x = np.random.default_rng(3).normal(size=(800, 3)) + 6 * np.random.default_rng(4).integers(0, 3, (800, 1))
    f = DriftForge(1.0, 3, 1, mode=mode).next(x)
    k, d2 = nearest(x, f.centroids)
    ratio = nearest(f.points, f.centroids)[1].mean() / d2.mean()
    assert f.magnitude.converged and abs(ratio / 2 - 1) < 0.05
    for c in range(3):
        moves = (f.points - x)[k == c]
        assert np.allclose(moves, moves[0])
    assert np.allclose(np.linalg.norm(unit_directions(5, 7, 1), axis=1), 1)
    far = DriftForge(1.0, 3, 1, mode=mode).next(frame(spark, x).persist())
    assert far.magnitude.converged and abs(far.magnitude.ratio / 2 - 1) < 0.05 and far.points.count() == 800


def test_literal_scale_reports_that_it_crawls():
    x = np.random.default_rng(3).normal(size=(5000, 2))
    m = DriftForge(1.0, 2, 1, scale="literal", max_steps=30).next(x).magnitude
    assert not m.converged and m.steps == 30
    assert search_alpha(lambda a: [4.0 + v * v for v in a], 4.0, 1.0, 1, 10).converged


def test_batching(spark):
    df = spark.range(1000).where("id % 7 <> 3").withColumn("v", F.col("id"))
    got = batching.by_ordinal(df, ["id"], 50).groupBy("batch_seq").count().collect()
    assert sorted(r["count"] for r in got)[:-1].count(50) >= len(got) - 2 and len(got) == 18
    plan = batching.by_dense_id(df, "id", 10)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    cal = {r["batch_seq"]: r for r in batching.calendar(spark, 20, 10, burn_in=5).collect()}
    assert cal[4]["concept_id"] == 0 and cal[5]["is_drift"] and cal[14]["t_index"] == 10 and cal[15]["concept_id"] == 2


def test_feature_specs(spark, sf_dir):
    for name, (d, view) in features.VIEWS.items():
        row = view(spark, sf_dir).first()
        assert len(row["x"]) == d and all(math.isfinite(v) for v in row["x"]), name
    df = spark.createDataFrame([(1, 1.0), (2, None), (3, float("nan"))], "id long, a double")
    spec = lambda p: features.FeatureSpec((("a", F.col("a")),), p)
    assert spec("drop").view(df, F.col("id")).count() == 1
    assert spec("impute").view(df, F.col("id")).agg(F.sum(F.col("x")[0])).first()[0] == 1.0
    with pytest.raises(Exception, match="missing or infinite"):
        spec("error").view(df, F.col("id")).collect()


def test_estimator(spark, tmp_path):
    data = batches(4, size=60)
    df = None
    for i, x in enumerate(data):
        one = frame(spark, x, i)
        df = one if df is None else df.union(one)
    df = df.withColumnRenamed("x", "features")
    est = FadingKMeans(k=3, rho=0.5, tMax=3)
    est.write().overwrite().save(str(tmp_path / "est"))
    model = FadingKMeans.load(str(tmp_path / "est")).fit(df)
    model.write().overwrite().save(str(tmp_path / "model"))
    again = FadingKMeansModel.load(str(tmp_path / "model"))
    assert np.allclose(again.centroids, model.centroids)
    assert again.transform(df).select("prediction").distinct().count() == 3


def test_grid_shows_the_reported_behaviour(spark, sf_dir):
    facts = run_grid(spark, sf_dir.replace("sf0.001", "sf0.01"), ["lineitem2", "embed50"], eps=(1.0,), ks=(5,), reps=2, n=150, concepts=4, limit=4000).persist()
    part = ["run_id", "dataset", "eps", "k", "m", "rep", "batch_seq"]

    def medians(metric, methods, index):
        scored = rel_excess(facts.where((F.col("metric") == metric) & F.col("t_index").isin(index)), part, methods)
        return {r["method"]: r["med"] for r in boxplot_summary(scored, ["method"]).collect()}

    four = ["carry", "fresh", "blend", "pair"]
    later = medians("init_faded", four, [4, 10])
    assert later["carry"] == min(later.values())
    end = medians("final_faded", four, [1, 2, 4, 10])
    assert end["pair"] <= 0.05
    spent = facts.where("metric = 'distances'").groupBy("method").agg(F.percentile("value", F.lit(0.5)).alias("m")).collect()
    spent = {r["method"]: r["m"] for r in spent}
    assert spent["carry"] <= min(spent[m] for m in ("fresh", "blend", "pair"))
    first = medians("since_drift", [*four, "reference"], [1])
    assert first["reference"] <= min(first[m] for m in four) + 0.05


def test_gap_experiment_is_covered(spark, sf_dir):
    g = gap_experiment(spark, sf_dir, n=100, limit=4000, reps=8)
    cover = {r["delta"]: r["c"] for r in g.groupBy("delta").agg(F.avg(F.col("inside").cast("double")).alias("c")).collect()}
    assert cover[0.05] >= 0.9 and cover[0.32] >= 0.6
    by_t = {r["t"]: r["m"] for r in g.groupBy("t").agg(F.avg("gap").alias("m")).collect()}
    assert by_t[1] > by_t[5] > by_t[15] - 0.05


def test_stream_equals_steps(spark, tmp_path):
    data = batches(4, size=50)
    for x in data:
        frame(spark, x).drop("batch_seq").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    root = str(tmp_path / "w")
    seen = []
    stream = fit.file_stream(spark, str(tmp_path / "in"), "point_id string, x array<double>")
    f = FadingClusterer(3, 0.5, 3, "carry", store=WindowStore(spark, root))
    fit.fit_stream(stream, f, str(tmp_path / "cp"), seen.append).awaitTermination()
    assert [r.seq for r in seen] == [0, 1, 2, 3]
    stored = [np.array([r["x"] for r in spark.read.parquet(f"{root}/points/batch_seq={s}").collect()]) for s in (1, 2, 3)]
    s = LocalWindow(np.concatenate(stored), np.repeat([1, 2, 3], 50)).passes([seen[-1].centroids])[0]
    assert math.isclose(s.error(fading(s.seqs, 3, 0.5)), seen[-1].final_faded, rel_tol=1e-9)
    again = FadingClusterer(3, 0.5, 3, "carry", store=WindowStore(spark, root))
    assert again.resume() == 3


def test_silhouette():
    x = np.array([[0.0], [1.0], [10.0], [11.0]])
    a, b = 1.0, 10.5
    want = np.mean([(b - a) / b, (9.5 - a) / 9.5, (9.5 - a) / 9.5, (b - a) / b])
    assert math.isclose(silhouette(x, np.array([0, 0, 1, 1])), want)


def test_entry(spark):
    out = __spark_entry__.entry(spark)
    assert out.count() == 10 * 5 * 4 and out.columns[:3] == ["batch_seq", "method", "k"]


TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


SLOW = {"features_star18", "drift_oracle_replay_5"}


@pytest.mark.parametrize("name", sorted(set(catalogue.SQL) - SLOW))
def test_queries_equal_sql(spark, duck, sf_dir, name):
    got = catalogue.QUERIES[name](spark, sf_dir)
    result = duck.execute(catalogue.SQL[name])
    cols = [d[0] for d in result.description]
    assert sorted(cols) == sorted(got.columns)
    order = sorted(cols)
    show = lambda v: repr(v) if isinstance(v, float) else str(v)
    a = sorted(tuple(show(r[c]) for c in order) for r in got.collect())
    b = sorted(tuple(show(r[cols.index(c)]) for c in order) for r in result.fetchall())
    assert a == b


def test_normality_reads_every_point(spark):
    """The first 5000 points are one normal lump, the rest another: all of them decide, in whatever order they lie."""
    from fadestream.operators.kchoice import choose_k

    rng = np.random.default_rng(5)
    x = np.concatenate([rng.normal(0, 1, 5000), rng.normal(9, 1, 5000)])
    df = spark.createDataFrame([(i, [float(v)]) for i, v in enumerate(x)], "point_id long, x array<double>").coalesce(1)
    assert choose_k(df, 4, "normal_split")[0] == 2


def test_bound_holds_and_reassigned_mass_is_counted(spark):
    rng = np.random.default_rng(5)
    for start in ("fresh", "blend", "pair"):
        f = FadingClusterer(3, 0.5, 3, start, c0_refine="mean", recenter_past=True, track_bound=True)
        for s in range(6):
            x = rng.normal(size=(60, 2)) + rng.integers(0, 3, size=(60, 1)) * 4 + s
            before, held = f.centroids, [(q, y) for q, y in f.held if q > s - 3]
            r = f.step(x, s)
            if s == 0:
                assert bound_slack(r) is None
                continue
            assert bound_slack(r) >= -1e-9 and 0 <= r.detail["reassigned"] <= 1
            near = lambda a, b: ((a[:, None] - b[None]) ** 2).sum(axis=2).argmin(axis=1)
            home = near(r.past.c, r.start)
            moved = sum(0.5 ** (s - q) * (home[near(y, before)] != near(y, r.start)).sum() for q, y in held)
            assert r.detail["reassigned"] * r.mass >= moved - 1e-9  # the older batches' part; the new batch adds to it


def test_stored_points_must_be_finite(spark, tmp_path):
    f = FadingClusterer(2, 0.5, 3, store=WindowStore(spark, f"{tmp_path}/w"))
    good = spark.createDataFrame([("a", [1.0]), ("b", [2.0]), ("c", [5.0])], "point_id string, x array<double>")
    f.step(good, 0)
    with pytest.raises(ValueError, match="finite"):
        f.step(spark.createDataFrame([("d", [float("nan")])], good.schema), 1)
    assert f.store.batches() == [0] and f.step(good, 1).mass == 4.5


@pytest.mark.parametrize("seeding", ["kmpp", "forgy", "parallel", "mcmc"])
def test_seeds_are_the_same_in_memory_and_stored(spark, tmp_path, seeding):
    df = frame(spark, batches(1, size=150, k=4)[0]).persist()
    here = FadingClusterer(4, 0.5, 3, seed=5, seeding=seeding)
    far = FadingClusterer(4, 0.5, 3, seed=5, seeding=seeding, store=WindowStore(spark, f"{tmp_path}/w"))
    a, b = here.step(df, 0), far.step(df, 0)
    assert np.allclose(a.start, b.start) and np.allclose(a.centroids, b.centroids)
    assert len(np.unique(a.start, axis=0)) == 4
    assert FadingClusterer(2, 0.5, 3, seeding=seeding).step(np.ones((5, 1)), 0).centroids.tolist() == [[1.0], [1.0]]


def test_late_rows_stay_late_after_a_restart(spark, tmp_path):
    got = {"kept": [], "late": []}
    to = lambda name: lambda df, epoch: got[name].extend((r["id"], r["batch_seq"]) for r in df.collect())

    def arrive(rows):
        spark.createDataFrame(rows, "id long, at timestamp").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        stream = fit.file_stream(spark, f"{tmp_path}/in", "id long, at timestamp")
        fit.fit_event_time(stream, "at", 10, 2, to("kept"), to("late"), f"{tmp_path}/cp").awaitTermination()

    when = lambda s: datetime.datetime.fromtimestamp(s, datetime.UTC)
    arrive([(1, when(5)), (2, when(95))])
    arrive([(3, when(85)), (4, when(75)), (5, when(101))])
    arrive([(6, when(85))])
    assert got["late"] == [(4, 7), (6, 8)]
    assert sorted(got["kept"]) == [(1, 0), (2, 9), (3, 8), (5, 10)]


def test_least_value_of_zero_divides_as_doubles(spark, tmp_path):
    rows = [(0, "a", 0.0), (1, "a", 2.0), (2, "a", None), (3, "b", 0.5), (4, "b", 2.0), (5, "c", -1.0), (6, "c", 0.0)]
    spark.createDataFrame(rows, "event_id long, event_type string, value double").write.parquet(str(tmp_path / "events.parquet"))
    got = {r["id"]: r["ratio"] for r in catalogue.QUERIES["win_min_norm"](spark, str(tmp_path)).collect()}
    want = dict(duckdb.sql(catalogue.SQL["win_min_norm"].replace("events", f"'{tmp_path}/events.parquet/*.parquet'")).fetchall())
    assert got.keys() == want.keys() and math.isnan(got[0]) and math.isnan(want[0])
    assert {i: v for i, v in got.items() if i} == {i: v for i, v in want.items() if i} and got[1] == math.inf


def test_a_small_window_sums_as_any(spark):
    rng = np.random.default_rng(3)
    for d, k in ((1, 1), (4, 5), (8, 3)):
        x, seq = np.round(rng.normal(size=(600, d)) * 20), rng.integers(0, 4, 600)
        for c in (x[:k], np.zeros((k, d)), rng.normal(size=(k, d))):
            a, b = LocalWindow(x, seq).passes([c])[0], sums_of(x, seq, c)
            assert all(np.array_equal(u, v) for u, v in ((a.seqs, b.seqs), (a.n, b.n), (a.sx, b.sx), (a.sxx, b.sxx))) and np.allclose(a.sse, b.sse, rtol=1e-12)


@pytest.mark.parametrize("scale", [3, 400])
def test_a_growing_window_steps_as_a_plain_one(scale):
    rng = np.random.default_rng(scale)
    plain, grown = (FadingClusterer(4, 1.0, None, "carry", grown=g) for g in (None, GrowingWindow(4, 3)))
    for s in range(90):
        x = np.round(rng.normal(size=(0 if s in (7, 8, 9, 10, 40) else 60, 3)) * scale + (s // 30) * scale)
        a, b = plain.step(x, s), grown.step(x, s)
        assert (a is None) == (b is None)
        if a is not None:
            assert np.array_equal(a.centroids, b.centroids) and a.iterations == b.iterations and a.total_distances == b.total_distances and a.mass == b.mass
            assert np.allclose([a.init_faded, a.final_faded, a.since_drift(s - s % 3)], [b.init_faded, b.final_faded, b.since_drift(s - s % 3)], rtol=1e-9)
    assert (grown.grown.mark[: grown.grown.n] > grown.grown.way).mean() > 0.9


@pytest.mark.parametrize("name", ["fading_run_carry", "fading_run_fresh", "fading_run_blend", "fading_run_pair", "drift_oracle_run", "static_run", "newest_only_run", "pair_greedy_run", "pair_identity_run", "blend_restarts_run", "pair_lloyd_refined_run"])
def test_runs_equal_single_steps(spark, tmp_path, monkeypatch, name):
    """The steps of a run over batches with holes, in whatever order the rows lie, against one clusterer stepped batch by batch."""
    n = 70 * 20
    e = spark.range(n).where("id div 20 not in (10, 11, 50, 51)").select(F.col("id").alias("event_id"), F.expr("timestamp_ntz'2024-01-01 00:00:00' + make_dt_interval(0, 0, id * 37)").alias("ts"), F.expr("(id * 7919 % 1009) / 10D").alias("value"), F.expr("concat('{\"k\": ', id * 31 % 97, '}')").alias("props"))
    e.orderBy(F.xxhash64("event_id")).write.parquet(str(tmp_path / "events.parquet"))
    monkeypatch.setattr(methods, "N", 20)
    f, want = methods.RUNS[name](), []
    points = {s: [] for s in range(70)}
    for r in methods.ev(spark, str(tmp_path)).collect():
        points[r["batch_seq"]].append((r["point_id"], r["x"]))
    for s in range(70):
        ids, x = zip(*sorted(points[s]), strict=True) if points[s] else ((), ())
        x = np.array(x, dtype=float).reshape(-1, 4)
        seeds = held_kmpp(HeldPoints(x, list(ids), s), 5) if len(x) else None
        r = f.step(x, s % 10 == 0, s, seeds) if isinstance(f, DriftOracleClusterer) else f.step(x, s, seeds=seeds)
        if r is not None:
            want.append((s, r.method, r.init_faded, r.final_faded, r.since_drift(s - s % 10), r.iterations, r.total_distances, r.mass))
    got = sorted(tuple(r) for r in catalogue.QUERIES[name](spark, str(tmp_path)).collect())
    assert len(got) == len(want) == 66
    for a, b in zip(got, want, strict=True):
        assert a[:2] == b[:2] and a[5:7] == b[5:7] and np.allclose(a[2:5] + a[7:], b[2:5] + b[7:], rtol=1e-12)


@pytest.mark.parametrize("name", ["calendar", "choose_rho_grid", "gap_interval_grid", "gap_interval_finite", "truncation_mass", "hoeffding_halfwidth", "rho_tradeoff", "distance_ledger", "recursive_powers", "source_rate_demo"])
def test_theory_and_sources_read_tables(spark, sf_dir, tmp_path, name):
    """Of half a table the result is another."""
    for t, by in (("events", "event_id < 400"), ("lineitem", "l_shipdate < timestamp_ntz'1998-01-01' and l_quantity < 25")):
        spark.read.parquet(f"{sf_dir}/{t}.parquet").where(by).write.parquet(str(tmp_path / f"{t}.parquet"))
    whole, part = ({tuple(r) for r in catalogue.QUERIES[name](spark, d).collect()} for d in (sf_dir, str(tmp_path)))
    assert whole and part and whole != part


def test_growing_window_keeps_few_candidates():
    """Once the list of next candidates had been made wide, while there were few points, passes looked through all marks."""
    rng = np.random.default_rng(4)
    grown, plain = GrowingWindow(3, 2), []
    f = FadingClusterer(3, 1.0, None, "carry", grown=grown)
    grown.AHEAD = 500
    listed = []
    for s in range(60):
        x = np.rint(rng.normal(scale=30, size=(200, 4)) + 100 * rng.integers(0, 3, 200)[:, None])
        plain.append(x)
        r = f.step(x, s, seeds=plain[0][[0, 50, 100]])
        horizon, near = grown._ahead()
        listed.append(len(near))
        late = np.setdiff1d(np.arange(grown.n), near)
        assert (grown.mark[late] > horizon).all() and horizon >= grown.way  # no point is left out
    assert max(listed[20:]) < 3000 < grown.n
    want = sums_of(np.concatenate(plain), np.zeros(grown.n, dtype=int), r.centroids)
    assert (r.sums.n.sum(axis=0) == want.n[0]).all() and np.allclose(r.sums.sx.sum(axis=0), want.sx[0], rtol=0, atol=0)
