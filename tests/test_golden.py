"""Hand-sized cases with exact values, identities on random data, and the laws of the seedings."""

import math
from fractions import Fraction as Fr

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from fadestream.functions import theory as th
from fadestream.functions.kernels import fading, nearest, nearest_two, sums_of
from fadestream.operators import matching as mt
from fadestream.operators.engine import FadingClusterer, bound_const
from fadestream.operators.errors import sse_from_sums, within_scatter
from fadestream.operators.lloyd import LocalWindow, lloyd, lloyd_many, lloyd_points
from fadestream.operators.seeding import fill, local_kmpp
from fadestream.operators.starts import BlendSeed, Centres, PairSeed, fresh_centres, past_centres, past_weights

OLD2 = np.array([(0, 0), (0, 2), (10, 0), (10, 2)], dtype=float)
OLD1 = np.array([(0, 1), (2, 1), (10, 1), (12, 1)], dtype=float)
NEW = np.array([(4, 0), (4, 2), (14, 0), (14, 2)], dtype=float)
WINDOW = LocalWindow(np.concatenate([OLD2, OLD1, NEW]), np.repeat([0, 1, 2], 4))
RNG = np.random.default_rng(0)


def fade(cur, rho=0.5):
    return lambda s: fading(s, cur, rho)


def past():
    two = LocalWindow(np.concatenate([OLD2, OLD1]), np.repeat([0, 1], 4))
    return lloyd(two, np.array([(0.0, 0), (10, 0)]), fade(1))


def error(c, t=None, rho=0.5):
    s = WINDOW.passes([np.asarray(c, dtype=float)])[0]
    if t is not None:
        s = s.keep(s.seqs > 2 - t)
        return s.error(np.ones(len(s.seqs)))
    return s.error(fading(s.seqs, 2, rho))


def test_three_small_batches():
    r = past()
    assert np.allclose(r.centroids, [(2 / 3, 1), (32 / 3, 1)]) and r.iterations == 2
    p = past_centres(r.centroids, r.sums, 2, 0.5, None, False)
    assert p.w.tolist() == [1.5, 1.5] == past_weights(r.sums, 2, 0.5, None).tolist()
    fresh, _ = fresh_centres(LocalWindow(NEW, np.full(4, 2)), np.array([(4.0, 0), (14, 0)]), "mean")
    assert fresh.c.tolist() == [[4, 1], [14, 1]] and fresh.w.tolist() == [2, 2]
    assert p.w.sum() + fresh.w.sum() == 7
    cost = mt.pair_cost(p.c, p.w, fresh.c, fresh.w)
    assert np.allclose(cost, [[200 / 21, 3200 / 21], [800 / 21, 200 / 21]])
    start = PairSeed().start(p, fresh, 7.0, RNG)
    assert start.detail["sigma"] == [0, 1] and np.isclose(start.detail["bound"], 400 / 147)
    blend = BlendSeed("past").start(p, fresh, 7.0, RNG)
    for c in (start.c, blend.c):
        assert np.allclose(c, [(18 / 7, 1), (88 / 7, 1)])
    sets = (p.c, fresh.c, start.c)
    assert np.allclose([error(c) for c in sets], [67 / 9, 41 / 7, 187 / 49])
    assert np.allclose([error(c, 1) for c in sets], [109 / 9, 1, 149 / 49])
    assert np.allclose([error(c, 3) for c in sets], [44 / 9, 28 / 3, 692 / 147])
    f = [mt.seed_bound(p.c, p.w, fresh.c, fresh.w, c, 7.0) for c in sets]
    const = bound_const(r.sums, LocalWindow(NEW, np.full(4, 2)).passes([fresh.c])[0], 0.5, 2, 7.0)
    assert np.allclose(f, [400 / 63, 100 / 21, 400 / 147]) and np.isclose(const, 23 / 21)
    assert np.allclose(np.array(f) + const, [error(c) for c in sets])
    for c in sets:
        end = lloyd(WINDOW, c, fade(2))
        assert np.allclose(end.centroids, [(18 / 7, 1), (88 / 7, 1)]) and np.isclose(end.errors[-1], 187 / 49) and end.iterations == 2
        assert end.sums.n.sum(axis=0).tolist() == [6, 6] and end.distances == 2 * 12 * 2


C_PAST, W_PAST = np.array([(0.0, 0), (2, 0), (20, 0)]), np.array([4.0, 1, 3])
C_FRESH, W_FRESH = np.array([(21.0, 0), (19, 0), (1, 0)]), np.array([2.0, 3, 5])


def test_three_centroids_that_cross():
    cost = mt.pair_cost(C_PAST, W_PAST, C_FRESH, W_FRESH)
    assert np.allclose(cost, [[588, 4332 / 7, 20 / 9], [722 / 3, 867 / 4, 5 / 6], [6 / 5, 3 / 2, 5415 / 8]])
    sums = {(0, 1, 2): Fr(11853, 8), (0, 2, 1): Fr(1771, 3), (1, 0, 2): Fr(258115, 168), (1, 2, 0): Fr(130387, 210), (2, 0, 1): Fr(4399, 18), (2, 1, 0): Fr(39631, 180)}
    for perm, value in sums.items():
        assert math.isclose(sum(cost[i, j] for i, j in enumerate(perm)), float(value))
    sigma, value = mt.solve_assignment(cost)
    assert sigma.tolist() == [2, 1, 0] and math.isclose(value, 39631 / 180)
    pair = PairSeed().start(Centres(C_PAST, W_PAST), Centres(C_FRESH, W_FRESH), 1.0, RNG)
    assert np.allclose(pair.c, [(5 / 9, 0), (59 / 4, 0), (102 / 5, 0)])
    assert math.isclose(mt.seed_bound(C_PAST, W_PAST, C_FRESH, W_FRESH, pair.c, 1.0), 23062 / 2025)
    assert math.isclose(mt.seed_bound_paired(C_PAST, W_PAST, C_FRESH, W_FRESH, pair.c, sigma, 1.0), 39631 / 180)
    for inner, centres, f in (("past", [(5 / 9, 0), (2, 0), (159 / 8, 0)], 511 / 72), ("fresh", [(102 / 5, 0), (19, 0), (7 / 10, 0)], 53 / 10), ("pair", None, 359 / 40)):
        got = BlendSeed(inner).start(Centres(C_PAST, W_PAST), Centres(C_FRESH, W_FRESH), 1.0, RNG).c
        if centres:
            assert np.allclose(got, centres)
        assert math.isclose(mt.seed_bound(C_PAST, W_PAST, C_FRESH, W_FRESH, got, 1.0), f)
    best = BlendSeed("kmpp", restarts=30).start(Centres(C_PAST, W_PAST), Centres(C_FRESH, W_FRESH), 1.0, RNG)
    assert best.detail["bound"] <= 53 / 10 + 1e-9


def test_scalar_functions():
    assert [round(th.choose_rho(e, t, m), 4) for e, t, m in ((0.5, 10, 2), (1, 10, 2), (2, 10, 2), (0.5, 20, 2), (0.5, 20, 1))] == [0.4573, 0.3981, 0.3466, 0.6762, 0.8223]
    assert th.choose_rho(0.005, 10, 2) == 1.0
    table = {(0.676, 1000): [0.03171, 0.01665, 0.00958, 0.01340, 0.01626], (0.676, 4000): [0.01586, 0.00832, 0.00479, 0.00670, 0.00813], (0.822, 1000): [0.03699, 0.02246, 0.00939, 0.00691, 0.00957]}
    for (rho, n), row in table.items():
        assert [round(th.drift_gap_interval(rho, t, n, 1, 0.5, 1, 0.05)[1], 5) for t in (1, 2, 5, 10, 20)] == row
    assert [th.choose_t_max(r) for r in (0.457, 0.398, 0.347)] == [12, 10, 9]
    with pytest.raises(ValueError):
        th.choose_t_max(1.0)


@pytest.mark.parametrize(("rho", "w", "t"), [(0.5, 12, 3), (0.8, 30, 7), (0.9, 20, 20)])
def test_interval_forms_agree(rho, w, t):
    _, half, lo, hi = th.drift_gap_interval_finite([100] * w, t, rho, 2.0, 0.5, 3.0, 0.1)
    centre, closed = th.drift_gap_equal_window(w, t, 100, rho, 2.0, 0.5, 3.0, 0.1)
    assert math.isclose(half, closed, rel_tol=1e-9) and math.isclose((lo + hi) / 2, centre, rel_tol=1e-9, abs_tol=1e-12)
    endless = th.drift_gap_interval_finite([100] * 600, t, rho, 2.0, 0.5, 3.0, 0.1)
    assert np.allclose(endless, th.drift_gap_interval(rho, t, 100, 2.0, 0.5, 3.0, 0.1))
    assert math.isclose(th.drift_gap_interval(rho, t, 100, 1, 1, 1, 0.1)[1], 2 * th.drift_gap_interval(rho, t, 400, 1, 1, 1, 0.1)[1])


def test_interval_covers():
    rng, rho, n, eps, inside = np.random.default_rng(3), 0.6, 200, 0.5, {0.05: 0, 0.32: 0}
    old, new = rng.random(5000), rng.random(5000) * (1 + eps)
    for _ in range(200):
        sums = [rng.choice(old, n).mean() for _ in range(30)] + [rng.choice(new, n).mean() for _ in range(4)]
        w = rho ** np.arange(len(sums))[::-1]
        gap = np.mean(sums[-4:]) - (w * sums).sum() / w.sum()
        for delta in inside:
            _, _, lo, hi = th.drift_gap_interval(rho, 4, n, 1 + eps, new.mean() / old.mean() - 1, old.mean(), delta)
            inside[delta] += lo < gap < hi
    assert inside[0.05] >= 0.92 * 200 and inside[0.32] >= 0.65 * 200


points = st.integers(2, 40).flatmap(lambda n: st.lists(st.tuples(*[st.integers(-20, 20)] * 3), min_size=n, max_size=n))


@settings(max_examples=40, deadline=None)
@given(points, st.integers(1, 5), st.floats(0.1, 1.0))
def test_identities(rows, k, rho):
    x = np.array(rows, dtype=float)
    seq = np.arange(len(x)) % 4
    c = fill(np.unique(x, axis=0)[:k], k)
    kk, d2 = nearest(x, c)
    brute = ((x[:, None, :] - c[None]) ** 2).sum(axis=2)
    assert np.allclose(d2, brute.min(axis=1)) and np.array_equal(kk, brute.argmin(axis=1))
    s = sums_of(x, seq, c)
    w = fading(s.seqs, int(seq.max()), rho)
    assert np.allclose(sse_from_sums(s, c), s.sse, atol=1e-6)
    mass = (w[:, None] * s.n).sum()
    new = s.seqs == s.seqs.max()
    split = (w[~new][:, None] * s.n[~new]).sum() / mass * (s.keep(~new).error(w[~new]) if (~new).any() else 0) + (w[new][:, None] * s.n[new]).sum() / mass * s.keep(new).error(w[new])
    assert np.isclose(split, s.error(w))
    r = lloyd(LocalWindow(x, seq), c, lambda q: fading(q, int(seq.max()), rho))
    assert all(a >= b - 1e-9 for a, b in zip(r.errors, r.errors[1:], strict=False))
    counts, sx = r.sums.weighted(fading(r.sums.seqs, int(seq.max()), rho))
    some = counts > 0
    assert np.allclose(sx[some] / counts[some][:, None], r.centroids[some], atol=1e-7)
    assert within_scatter(r.sums, w) >= -1e-6


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 6).flatmap(lambda n: st.lists(st.lists(st.one_of(st.integers(0, 5), st.floats(0, 100)), min_size=n, max_size=n), min_size=n, max_size=n)))
def test_assignment_is_optimal(rows):
    cost = np.array(rows, dtype=float)
    sigma, value = mt.solve_assignment(cost)
    assert sorted(sigma.tolist()) == list(range(len(cost)))
    assert math.isclose(value, mt.brute_force_assignment(cost)[1], rel_tol=1e-9, abs_tol=1e-9)
    assert value <= mt.greedy_assignment(cost)[1] + 1e-9 and value <= mt.identity_assignment(cost)[1] + 1e-9


def test_assignment_of_odd_input():
    with pytest.raises(ValueError):
        mt.solve_assignment(np.zeros((2, 3)))
    big = np.random.default_rng(1).random((60, 60))
    assert mt.solve_assignment(big)[1] <= mt.greedy_assignment(big)[1]


def test_merged_pairs_beat_perturbations():
    rng = np.random.default_rng(5)
    sigma = np.array([2, 1, 0])
    c = mt.combine_pairs(C_PAST, W_PAST, C_FRESH, W_FRESH, sigma)
    f = mt.seed_bound_paired(C_PAST, W_PAST, C_FRESH, W_FRESH, c, sigma, 1.0)
    for _ in range(1000):
        assert mt.seed_bound_paired(C_PAST, W_PAST, C_FRESH, W_FRESH, c + rng.normal(scale=0.5, size=c.shape), sigma, 1.0) >= f
    zero = mt.combine_pairs(C_PAST, np.zeros(3), C_FRESH, np.zeros(3), sigma)
    assert np.array_equal(zero, C_PAST) and mt.pair_cost(C_PAST, np.zeros(3), C_FRESH, np.zeros(3)).sum() == 0


def test_bound_holds_for_means_only():
    rng = np.random.default_rng(8)
    for _ in range(30):
        old, new = rng.normal(size=(60, 2)) * 3, rng.normal(size=(30, 2)) * 3 + 1
        seq = np.repeat([0, 1], 30)
        r = lloyd(LocalWindow(old, seq), local_kmpp(old, 4, rng), fade(1, 0.6))
        p = past_centres(r.centroids, r.sums, 2, 0.6, None, True)
        newest = LocalWindow(new, np.full(30, 2))
        seeds = local_kmpp(new, 4, rng)
        fresh, _ = fresh_centres(newest, seeds, "mean")
        mass = p.w.sum() + fresh.w.sum()
        const = bound_const(r.sums, newest.passes([seeds])[0], 0.6, 2, mass)
        window = LocalWindow(np.concatenate([old, new]), np.concatenate([seq, np.full(30, 2)]))
        for _ in range(10):
            c = rng.normal(size=(4, 2)) * 3
            s = window.passes([c])[0]
            assert s.error(fading(s.seqs, 2, 0.6)) <= mt.seed_bound(p.c, p.w, fresh.c, fresh.w, c, mass) + const + 1e-9


@pytest.mark.parametrize("power", [1, 2])
def test_seeding_law(power):
    x = np.array([0.0, 1, 2, 4, 7, 11, 16, 22])[:, None]
    rng, got = np.random.default_rng(2), np.zeros(8)
    n = 4000
    firsts = 0
    want = np.zeros(8)
    for _ in range(n):
        c = local_kmpp(x, 2, rng, power)
        got[np.flatnonzero(x[:, 0] == c[1, 0])[0]] += 1
        d = np.abs(x[:, 0] - c[0, 0]) ** power
        want += d / d.sum()
        firsts += c[0, 0]
    chi = ((got - want) ** 2 / want).sum()
    assert chi < 24.3  # 0.1 % of a chi square with 7 degrees


def test_edges():
    x = np.array([[1.0], [1.0], [3.0]])
    assert nearest(np.array([[2.0]]), np.array([[1.0], [3.0]]))[0][0] == 0
    assert nearest_two(np.array([[1.5]]), np.array([[1.0], [3.0]]))[2][0] == 2.0
    assert lloyd(LocalWindow(x, np.zeros(3, dtype=int)), np.array([[2.0]])).centroids[0, 0] == pytest.approx(5 / 3)
    r = lloyd(LocalWindow(x, np.zeros(3, dtype=int)), np.array([[1.0], [3.0], [99.0]]))
    assert r.centroids[2, 0] == 99.0
    assert len(local_kmpp(x, 5, RNG)) == 5
    f = FadingClusterer(2, 0.5, 1, "pair")
    assert f.step(np.empty((0, 1))) is None
    with pytest.raises(ValueError):
        f.step(np.array([[np.nan]]))
    for size in (1, 10, 1000):
        got = f.step(np.arange(size, dtype=float)[:, None])
        assert np.isfinite(got.final_faded)
    assert lloyd_points(np.array([[0.0], [4.0]]), np.array([1.0, 3.0]), np.array([[1.0]])).centroids[0, 0] == 3.0


def test_models_share_passes():
    rng = np.random.default_rng(4)
    w = LocalWindow(rng.normal(size=(300, 3)), np.repeat(np.arange(3), 100))
    starts = [local_kmpp(w.x, 4, rng) for _ in range(3)]
    many = lloyd_many(w, starts, fade(2))
    for one, s in zip(many, starts, strict=True):
        alone = lloyd(w, s, fade(2))
        assert np.allclose(one.centroids, alone.centroids) and one.iterations == alone.iterations and one.distances == alone.distances
