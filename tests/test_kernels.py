"""Bounds, splits and runs on arrays: identities, monotonicity, worked examples."""

import numpy as np
import pytest

from mts_search.functions import kernels as K

G = np.random.default_rng(1)


def walk(c, m):
    return np.cumsum(G.normal(size=(c, m)), axis=1)


@pytest.mark.parametrize("q", [8, 13, 52])
@pytest.mark.parametrize("normalized", [False, True])
def test_all_bins_give_the_distance(q, normalized):
    a, b = walk(3, q), walk(3, q)
    dims = K.dims_of(q, {c: list(range(K.bins_of(q))) for c in range(3)}, normalized)
    f = K.window_features(np.stack([a, b]), dims, normalized)
    x, y = (K.znorm(a), K.znorm(b)) if normalized else (a, b)
    assert ((f[0] - f[1]) ** 2).sum() == pytest.approx(((x - y) ** 2).sum(), rel=1e-9)


@pytest.mark.parametrize("normalized", [False, True])
def test_bound_grows_with_bins_and_stays_below(normalized):
    a, b = walk(2, 20), walk(2, 20)
    x, y = (K.znorm(a), K.znorm(b)) if normalized else (a, b)
    true, last = ((x - y) ** 2).sum(), 0.0
    for n in range(1, K.bins_of(20) + 1):
        dims = K.dims_of(20, {0: list(range(n)), 1: list(range(n))}, normalized)
        f = K.window_features(np.stack([a, b]), dims, normalized)
        lb = ((f[0] - f[1]) ** 2).sum()
        assert last - 1e-9 <= lb <= true * (1 + 1e-9) + 1e-9
        last = lb


@pytest.mark.parametrize("normalized", [False, True])
def test_sliding_features_match_single_windows(normalized):
    x = walk(2, 90) + 50
    x[1, 20:60] = 3.0
    dims = K.dims_of(16, {0: [0, 2, 8], 1: [1, 3]}, normalized)
    w = np.lib.stride_tricks.sliding_window_view(x, 16, axis=1).transpose(1, 0, 2)
    assert np.allclose(K.sliding_features(x, 16, dims, normalized), K.window_features(w, dims, normalized), atol=1e-6)


@pytest.mark.parametrize("normalized", [False, True])
def test_pivot_distances_need_no_remainder(normalized):
    x, q, kept = walk(2, 80) + 7, 20, {0: [0, 1], 1: [0, 3]}
    dims = K.dims_of(q, kept, normalized)
    w = np.lib.stride_tricks.sliding_window_view(x, q, axis=1).transpose(1, 0, 2)
    rest = K.remainder(w, kept, normalized)
    pivots = K.kmeans(rest.reshape(len(rest), -1), 2).reshape(-1, 2, q)
    want = np.sqrt(((rest[:, None] - pivots[None]) ** 2).sum(axis=3)).transpose(0, 2, 1).reshape(len(rest), -1)
    got = K.pivot_gaps(x, q, dims, K.sliding_features(x, q, dims, normalized), pivots, normalized)
    assert np.allclose(got, want, atol=1e-5)
    f = K.window_features(w, dims, normalized)
    z = K.znorm(w) if normalized else w
    for i in (3, 17):
        d2 = ((z - z[i]) ** 2).sum(axis=(1, 2))
        assert (((f - f[i]) ** 2).sum(axis=1) + ((want - want[i]) ** 2).reshape(len(rest), 2, 2).max(axis=2).sum(axis=1) <= d2 * (1 + 1e-9) + 1e-6).all()


@pytest.mark.parametrize("normalized", [False, True])
def test_profile_fft_equals_direct(normalized):
    x, y = walk(3, 400) + 1e4, walk(3, 30) + 1e4
    x[0, 100:160] = 5.0
    assert np.allclose(K.profile(x, y, normalized, "fft"), K.profile(x, y, normalized, "direct"), rtol=1e-6, atol=1e-4)


def test_runs_of_a_leaf():
    x, y = np.array([10, 11, 12]), np.array([40, 41])
    first, last = K.runs(np.concatenate([np.zeros(3), np.zeros(2)]) + np.concatenate([[0, 0, 0], [1, 1]]))
    starts = np.concatenate([x, y])
    assert [(int(starts[a]), int(starts[b])) for a, b in zip(first, last, strict=True)] == [(10, 12), (40, 41)]


def test_line_of_ten_in_leaves_of_two():
    pts = np.arange(1.0, 11.0)[:, None]
    leaf = K.route(pts, K.learn_router(pts, 10, 2, np.array([1.0])))
    assert [np.flatnonzero(leaf == i).tolist() for i in range(leaf.max() + 1)] == [[0, 1], [2, 3], [4, 5], [6, 7], [8, 9]]


def test_wide_dimension_gets_more_slices():
    pts = np.column_stack([G.uniform(2, 6, 500), G.uniform(1.5, 2.5, 500)])
    w = K.softmax_weights(pts.var(axis=0))
    counts = K.split_counts(w, 500, 10)
    assert counts[0] > counts[1] >= 1
    assert K.split_counts(np.array([0.5, 0.5]), 100, 1).tolist() == [10, 10]
    for layout in ("str", "kd"):
        leaf = K.route(pts, K.learn_router(pts, 500, 10, w, layout))
        assert np.bincount(leaf).max() <= 60


@pytest.mark.parametrize("strategy", ["quadratic", "linear", "topological"])
def test_split_of_an_overflowing_leaf_parts_two_clusters(strategy):
    lo = np.concatenate([G.uniform(0, 1, (6, 2)), G.uniform(9, 10, (6, 2))])
    side = K.split_node(np.stack([lo, lo + 0.1], axis=1), strategy)
    assert len(set(side[:6])) == 1 and len(set(side[6:])) == 1 and side[0] != side[6]


def test_segment_bounds_hold():
    x, q = walk(1, 200)[0], 24
    w = np.lib.stride_tricks.sliding_window_view(x, q)
    cuts = K.adaptive_cuts(w[::7], 5)
    for std in (False, True):
        f = K.segment_features(x, q, cuts, std)
        assert (((f - f[50]) ** 2).sum(axis=1) <= ((w - w[50]) ** 2).sum(axis=1) * (1 + 1e-9) + 1e-6).all()


def test_sinusoid_keeps_its_bin_only():
    from mts_search.operators.index import ardc, select_bins

    t = np.arange(40)
    s = np.stack([[a * np.sin(2 * np.pi * 3 * t / 40 + p)] for a, p in zip(G.uniform(1, 3, 20), G.uniform(0, 6, 20), strict=True)])
    assert select_bins(ardc(s), 0.9) == {0: [3]}
    back, err = K.reconstruct(s[0, 0], [3])
    assert err < 1e-9 and np.allclose(back, s[0, 0])


@pytest.mark.parametrize("normalized", [False, True])
def test_profiles_of_several_queries_equal_single_ones(normalized, monkeypatch):
    """The chunk is transformed once a channel for all queries, not once a query."""
    g = np.random.default_rng(3)
    x, ys = g.integers(0, 50, (2, 300)).astype(float), g.integers(0, 50, (5, 2, 40)).astype(float)
    singles = np.array([K.profile(x, y, normalized, "direct") for y in ys])
    for method in ("auto", "fft", "direct"):
        assert np.allclose(K.profiles(x, ys, normalized, method), singles, atol=1e-6)
    if not normalized:
        made, rfft = [], np.fft.rfft
        monkeypatch.setattr(np.fft, "rfft", lambda *a, **k: made.append(1) or rfft(*a, **k))
        K.profiles(x, ys)
        assert len(made) == 4
