"""Blocks of the experiment cells: whole views, in memory or in a file, with the results of the plain arrays."""

import inspect
import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from fadestream.functions import kernels
from fadestream.functions.kernels import Packed, sums_of
from fadestream.operators.blocks import PointBlock
from fadestream.operators.features import VIEWS, hash178
from fadestream.operators.forge import DriftForge
from fadestream.operators.lloyd import LocalWindow, lloyd
from fadestream.plans import catalogue
from fadestream.plans.experiments import run_cell, run_grid, whole_block
from fadestream.streaming import fit


def filled(x, held=None, step=7000):
    b = PointBlock(held)
    for i in range(0, len(x), step):
        b.add(x[i : i + step])
    return b.done()


def points(n, d, seed=1):
    rng = np.random.default_rng(seed)
    return rng.normal(scale=4.0, size=(6, d))[rng.integers(0, 6, n)] + rng.normal(size=(n, d))


@pytest.mark.parametrize("held", [None, 0, 3_000_000])
def test_forge_on_a_block_equals_the_array(held):
    x = points(40_000, 5)
    a, b = DriftForge(1.0, 5, 3), DriftForge(1.0, 5, 3)
    block = filled(x, held)
    assert (block.file is None) == (held is None)
    for _ in range(2):
        want, got = a.next(x), b.next(block)
        x, block = want.points, got.points
        assert np.allclose(want.centroids, got.centroids, atol=1e-9)
        assert abs(want.magnitude.alpha - got.magnitude.alpha) < 1e-9 and want.magnitude.steps == got.magnitude.steps
    at = np.array([39_999, 0, 16_384, 5, 16_383])
    assert np.allclose(block.rows(at), x[at], atol=1e-8)
    assert len(block) == len(x)


def test_block_passes_with_ties_few_points_and_one_cluster():
    x = np.array([[0.0, 0.0], [1.0, 0.0], [2.0, 0.0], [2.0, 0.0]])
    b = filled(x)
    for c in ([[0.0, 0.0], [2.0, 0.0]], [[2.0, 0.0], [0.0, 0.0]], [[1.0, 0.0], [1.0, 0.0]], [[0.5, 0.0]]):
        c = np.array(c)
        got, want = b.passes([c])[0], sums_of(x, np.zeros(4, dtype=int), c)
        assert (got.n == want.n).all() and np.allclose(got.sx, want.sx) and np.allclose(got.sse, want.sse)
    with pytest.raises(ValueError, match="finite"):
        b.add(np.array([[np.nan, 0.0]]))


def test_block_in_a_file_holds_a_chunk_not_the_block():
    x = points(300_000, 18)
    tracemalloc.start()
    b = filled(x, held=0)
    DriftForge(1.0, 5, 3, tol=0.5).next(b)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < x.nbytes / 2


def test_wide_windows_give_the_sums_of_the_plain_kernel():
    x = points(3000, 40)
    x[10:20] = x[0]
    seq = np.repeat(np.arange(6), 500)
    c = np.vstack([x[[0, 700, 1400]], x[0]])  # two equal centroids, on a point
    w = LocalWindow(x, seq)
    assert not isinstance(w.packed, Packed)
    got, want = w.passes([c])[0], sums_of(x, seq, c)
    assert (got.n == want.n).all()
    for name in ("sx", "sxx", "sse"):
        assert np.allclose(getattr(got, name), getattr(want, name), rtol=1e-9, atol=1e-9)
    mixed = np.random.default_rng(0).permutation(seq)
    assert np.allclose(LocalWindow(x, mixed).passes([c])[0].sx, sums_of(x, mixed, c).sx)


def test_cells_work_on_whole_views(spark, sf_dir):
    assert inspect.signature(run_grid).parameters["limit"].default is None
    big = sf_dir.replace("sf0.001", "sf0.01")
    df, n = whole_block(spark, big, "lineitem2")
    assert n == df.count() == VIEWS["lineitem2"][1](spark, big).count() > 20_000


def test_a_grid_has_all_cells_and_repeats(spark, sf_dir):
    def run():
        facts = run_grid(spark, sf_dir, ["lineitem2", "embed50"], eps=(0.5, 1.0), ks=(3,), n=60, concepts=1, period=2)
        return sorted(map(tuple, facts.collect()), key=str)

    one = run()
    assert len({(r[1], r[2]) for r in one}) == 4
    assert one == run()


@pytest.mark.parametrize("name", ["detector_ablation", "source_drift_forge"])
def test_forged_streams_are_made_of_events(spark, sf_dir, tmp_path, name):
    """Of part of the table the result is another; every batch is in it."""
    sf_dir = sf_dir.replace("sf0.001", "sf0.01")  # 50 batches
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    e.where("event_id < 4000").write.parquet(str(tmp_path / "events.parquet"))
    whole, part = (catalogue.QUERIES[name](spark, d).collect() for d in (sf_dir, str(tmp_path)))
    assert whole and part and sorted(map(tuple, whole)) != sorted(map(tuple, part))
    if name == "source_drift_forge":
        assert sum(r["n"] for r in whole) == e.count()
    else:
        error = {(r["p_false"], r["p_miss"]): r["error"] for r in whole}
        assert len(error) == 4 and error[0.0, 0.0] < error[0.0, 0.5]


@pytest.mark.parametrize("d", [2, 12, 40])
def test_followed_windows_have_the_sums_of_the_plain_kernel_and_look_at_few_points(d, monkeypatch):
    x, seq = points(6000, d), np.repeat(np.arange(12), 500)
    looked, plain = [], kernels.two_nearest
    monkeypatch.setattr(kernels, "two_nearest", lambda x, c, guess=None: looked.append(x.shape[1]) or plain(x, c, guess))
    window = LocalWindow(x, seq, narrow=False)
    for start in (x[:7], x[3000:3007], x[:7] + 0.01):  # the window goes on from where it was
        one, two = lloyd(window, start), lloyd(LocalWindow(x, seq, np.ones(len(x))), start)
        assert one.iterations == two.iterations and np.allclose(one.centroids, two.centroids, atol=1e-9)
        assert np.allclose(one.errors, two.errors, rtol=1e-11)
        for name in ("n", "sx", "sxx", "sse"):
            assert np.allclose(getattr(one.sums, name), getattr(two.sums, name), rtol=1e-9, atol=1e-9)
    assert 0 < sum(looked) < two.iterations * len(x) * 2


def test_policies_of_a_cell_share_their_window(monkeypatch):
    made = []
    init = kernels.Followed.__init__
    monkeypatch.setattr(kernels.Followed, "__init__", lambda self, x, seq: made.append(len(x)) or init(self, x, seq))
    cell = {"dataset": "x", "eps": 1.0, "k": 3, "m": 2, "rep": 0, "t_max": 4}
    run_cell(filled(points(3000, 20)), cell, n=50, concepts=1, period=3, tol=0.01, shared_from="best", start_options={})
    steps = 4 + 3
    assert sum(n > 50 for n in made) <= 2 * steps  # one of the policies, one of the reference


def test_words_of_one_doc_id_are_one_point(spark, tmp_path):
    rows = [(1, "A b  b"), (2, None), (3, " \t"), (4, "\u00c9 x"), (1, "a")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    got = {r["doc_id"]: r["x"] for r in hash178(spark, str(tmp_path)).collect()}
    assert set(got) == {1, 4}
    assert np.allclose(sorted(got[1])[-2:], [2 / 8**0.5] * 2) and all(abs(np.linalg.norm(x) - 1) < 1e-12 for x in got.values())


def test_views_of_texts_hash_a_word_once(spark, sf_dir):
    plan = hash178(spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert "md5" not in plan and "Generate" not in plan


def test_a_wrong_guess_and_ties_do_not_change_the_nearest():
    x = np.concatenate([points(5000, 3), np.zeros((3, 3))])
    c = np.vstack([x[:6], x[2], -np.ones(3), np.ones(3)])
    want = kernels.nearest(x, c)
    for guess in (None, np.full(len(x), 8), np.random.default_rng(0).integers(0, 9, len(x)), np.full(len(x), 6)):
        k, near, then = kernels.two_nearest(kernels.laid(x), c, guess)
        assert (k == want[0]).all() and np.allclose(near, want[1], atol=1e-9) and (then >= near).all()


def test_large_narrow_windows_are_followed(monkeypatch):
    """Every pass of keyed state took all points of its window by the plain kernel before."""
    x = np.rint(points(30_000, 4) * 10)
    seq = np.repeat([3, 4], 15_000)
    start = x[[0, 9000, 20_000]]
    want = lloyd(LocalWindow(x, seq, np.ones(len(x))), start, lambda s: 0.5 ** (4.0 - s))
    looked = []
    plain, two = kernels.sums_of, kernels.two_nearest
    monkeypatch.setattr("fadestream.operators.lloyd.sums_of", lambda x, *a: looked.append(len(x)) or plain(x, *a))
    monkeypatch.setattr(kernels, "two_nearest", lambda x, *a: looked.append(x.shape[1]) or two(x, *a))
    got = lloyd(LocalWindow(x, seq), start, lambda s: 0.5 ** (4.0 - s))
    assert got.iterations == want.iterations and (got.sums.n == want.sums.n).all()
    assert np.allclose(got.centroids, want.centroids, rtol=1e-12, atol=1e-9)
    assert np.allclose(got.sums.sse, want.sums.sse, rtol=1e-9)
    assert sum(looked) < len(x) * got.iterations / 2
    mixed = np.tile([4, 3], 15_000)
    assert np.allclose(LocalWindow(x, mixed).passes([start])[0].sx, plain(x, mixed, start).sx)


def test_keyed_points_travel_in_few_rows(spark, tmp_path):
    """A group of many rows goes to its function in chunks, each with the key's whole state: points of a key were rows of their own before."""
    x = np.rint(points(6000, 4))
    keys = ["a", "b", None]
    rows = [(keys[i % 3], v.tolist()) for i, v in enumerate(x)]
    df = spark.createDataFrame(rows, "u string, x array<double>").coalesce(2)
    got = fit._packed(df, "u").collect()
    assert len(got) <= 3 * 2
    for i, key in enumerate(keys):
        mine = np.concatenate([np.frombuffer(r["xs"]).reshape(-1, r["d"]) for r in got if r["key"] == key])
        assert sorted(map(tuple, mine)) == sorted(map(tuple, x[i::3]))
    for _ in range(3):
        df.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    out = fit.fit_keyed(fit.file_stream(spark, str(tmp_path / "in"), "u string, x array<double>"), "u", 3, 0.5, 2)
    q = out.writeStream.outputMode("append").format("memory").queryName("keyed_few").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert max(o["memoryUsedBytes"] for o in q.lastProgress["stateOperators"]) < 2.5 * x.nbytes  # two versions of one batch each, not of two
    facts = spark.table("keyed_few").groupBy("key", "batch_seq").agg(F.sum("n").alias("n")).collect()
    assert sorted((r["key"], r["batch_seq"], r["n"]) for r in facts) == [(k, b, 2000 if b == 0 else 4000) for k in ("None", "a", "b") for b in range(3)]
