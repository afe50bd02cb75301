import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from vecspark.functions.kernels import BatchPlan, CentroidBlocks, Work, assign_full, assign_pruned, elkan, hamerly, lloyd, pivot_scan, sq_dists, sq_norms, threshold
from vecspark.operators.clustering import adjust_head, repair_empty, share_k
from vecspark.operators.rotation import random_rotation, unrotate
from vecspark.operators.stopping import plateau


def naive(x, y):
    return ((x[:, None, :] - y[None, :, :]) ** 2).sum(2)


@pytest.fixture
def data():
    rng = np.random.default_rng(1)
    return rng.normal(size=(300, 200)), rng.normal(size=(37, 200))


def test_distances_through_products_equal_naive_ones(data):
    x, y = data
    assert np.allclose(sq_dists(x, y), naive(x, y))
    for d1 in (1, 25, 64, 199):
        assert np.allclose(sq_dists(x[:, :d1], y[:, :d1]) + sq_dists(x[:, d1:], y[:, d1:]), naive(x, y))


def test_rotation_is_orthogonal_and_reversible(data):
    x, y = data
    r = random_rotation(200, 4)
    assert np.abs(r @ r.T - np.eye(200)).max() < 1e-10
    assert np.allclose(sq_norms(x @ r), sq_norms(x))
    assert np.allclose(unrotate(y @ r, r), y)


def test_threshold_grows_and_ends_at_tau():
    t = [threshold(b, 64, 2.0) for b in range(1, 65)]
    assert t[-1] == 2.0 and threshold(8, 64, 2.0, np.inf) == np.inf
    assert all(threshold(b, 10_000, 2.0) < threshold(b + 100, 10_000, 2.0) for b in range(100, 9000, 100))


@pytest.mark.parametrize("plan", [BatchPlan(), BatchPlan(64, 5), BatchPlan(1, 1), BatchPlan(7, 100)])
@pytest.mark.parametrize("mode", ["head_nearest", "previous", "first_batch"])
@pytest.mark.parametrize("progressive", [True, False])
@pytest.mark.parametrize("refinement", ["pairs", "grouped"])
def test_without_pruning_every_shape_gives_the_nearest(data, plan, mode, progressive, refinement):
    x, y = data
    want = naive(x, y).argmin(1)
    assert (assign_full(x, y, plan)[0] == want).all()
    prev = np.random.default_rng(2).integers(0, len(y), len(x))
    cid, dist = assign_pruned(x, CentroidBlocks(y, 25, 64), prev, np.inf, progressive, mode, plan, refinement=refinement)
    assert (cid == want).all() and np.allclose(dist, naive(x, y).min(1))


def test_pruned_pair_is_never_assigned():
    # a partial distance below tau must not win once its pair has been given up
    rng = np.random.default_rng(3)
    r = random_rotation(128, 0)
    x, y = rng.normal(size=(500, 128)) @ r, rng.normal(size=(60, 128)) @ r
    exact = naive(x, y)
    cid, dist = assign_pruned(x, CentroidBlocks(y, 16, 16))
    assert np.allclose(dist, exact[np.arange(len(x)), cid])
    assert (cid != exact.argmin(1)).mean() < 0.01
    grouped, dist = assign_pruned(x, CentroidBlocks(y, 16, 16), refinement="grouped")
    assert np.allclose(dist, exact[np.arange(len(x)), grouped]) and (grouped != exact.argmin(1)).mean() < 0.01


def test_pruning_saves_work_where_clusters_are_clear():
    rng = np.random.default_rng(4)
    y = rng.normal(size=(64, 256)) * 3
    x = y[rng.integers(0, 64, 1000)] + rng.normal(size=(1000, 256)) * 0.3
    r = random_rotation(256, 1)
    full, phased, binary, rows = Work(), Work(), Work(), Work()
    assign_full(x @ r, y @ r, work=full)
    cid, _ = assign_pruned(x @ r, CentroidBlocks(y @ r, 32, 64), work=phased)
    assign_pruned(x @ r, CentroidBlocks(y @ r, 32, 64), progressive=False, work=binary)
    assign_pruned(x @ r, CentroidBlocks(y @ r, 32, 64, "rows"), work=rows)
    assert (cid == naive(x, y).argmin(1)).all()
    assert phased.head_mul_adds + phased.tail_mul_adds < 0.3 * full.head_mul_adds
    assert phased.tail_mul_adds <= binary.tail_mul_adds and rows.tail_mul_adds == phased.tail_mul_adds
    assert phased.rejected_head / phased.tested > 0.95


def test_ties_go_to_the_lower_centroid():
    x = np.ones((4, 8))
    y = np.ones((3, 8))
    for mode in ("head_nearest", "first_batch"):
        assert (assign_pruned(x, CentroidBlocks(y, 2, 2), seed_mode=mode)[0] == 0).all()
    assert (assign_full(x, y)[0] == 0).all()


@pytest.mark.parametrize("method", [elkan, hamerly])
def test_bounds_give_the_labels_of_plain_iterations(method):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(400, 12))
    y = x[:9]
    centroids = lloyd(x, y, 5)
    cid, got, done, pairs = method(x, y, 6)
    assert (cid == naive(x, centroids).argmin(1)).all()
    assert done <= pairs + len(x) * 6


@pytest.mark.parametrize("variant", ["each", "all"])
def test_pivot_scan_is_exact(variant):
    rng = np.random.default_rng(6)
    y = rng.normal(size=(25, 10)) * 4
    x = y[rng.integers(0, 25, 300)] + rng.normal(size=(300, 10)) * 0.2
    cid, dist, _ = pivot_scan(x, y, variant)
    assert (cid == naive(x, y).argmin(1)).all() and np.allclose(dist, naive(x, y).min(1))


def test_head_controller():
    d1, seen = 64, []
    for rate in (0.99, 0.99, 0.96, 0.90):
        d1 = adjust_head(d1, rate, 512)
        seen.append(d1)
    assert seen == [51, 40, 40, 48]
    assert adjust_head(60, 0.1, 64) == 64 and adjust_head(1, 0.99, 64) == 1


def test_recall_plateau_both_readings():
    series = [0.80, 0.85, 0.86, 0.862, 0.863]
    assert [plateau(series[:i], 0.005) for i in range(1, 6)] == [False, False, False, False, True]
    assert [plateau(series[:i], 0.005, rule="window") for i in range(1, 6)] == [False, False, False, False, True]


def test_split_fills_empties_and_keeps_the_mean():
    y, n = repair_empty(np.array([[1.0, 2.0], [9.0, 9.0]]), np.array([10, 0]), seed=1)
    assert (n > 0).all() and n.sum() == 10 and np.allclose(y.mean(0), [1.0, 2.0])
    assert np.allclose(repair_empty(np.zeros((2, 2)), np.array([3, 0]), "farthest", far=np.ones((1, 2)))[0][1], 1)


@settings(deadline=None, max_examples=60)
@given(st.lists(st.integers(1, 200), min_size=1, max_size=20), st.integers(1, 400))
def test_shares_add_up_and_stay_in_bounds(sizes, k):
    live = dict(enumerate(sizes))
    out = share_k(live, k)
    assert sum(out.values()) == max(len(live), min(k, sum(sizes)))
    assert all(1 <= out[c] <= live[c] for c in live)
