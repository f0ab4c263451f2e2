"""The sphere summarizer alone: conservation, capacity, weights, limits, state."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from kmfold.functions.arrays import block_distances
from kmfold.operators.clustering import kmeanspp_array
from kmfold.operators.sphere import FeatureTree, SphereTree, copies_that_fit, sampled_cells, sampling_coreset


def cloud(n, d, seed=0):
    return np.random.default_rng(seed).standard_normal((n, d))


@pytest.mark.parametrize("block", [1, 256])
@pytest.mark.parametrize("finder", ["full", "band", "auto"])
def test_conservation_and_capacity(block, finder):
    x = cloud(3000, 6)
    t = SphereTree(80, 6, 1, finder=finder, block=block)
    t.offer(x)
    mean, w, within = t.rows()
    assert len(w) <= 80 and w.sum() == 3000 and (w > 0).all()
    assert np.allclose((mean * w[:, None]).sum(0), x.sum(0))
    assert np.isclose((w * (mean**2).sum(1)).sum() + within.sum(), (x**2).sum())
    assert t.counters["rebuilds"] > 0


def test_band_finds_what_full_finds_in_order():
    x = cloud(1500, 4, 3)
    rows = []
    for finder in ("full", "band"):
        t = SphereTree(60, 4, 1, finder=finder, block=1)
        t.offer(x)
        rows.append(t.rows())
    assert np.allclose(rows[0][0], rows[1][0]) and (rows[0][1] == rows[1][1]).all()


def test_equal_points_are_one_feature():
    t = SphereTree(5, 3)
    t.offer(np.ones((1000, 3)))
    mean, w, within = t.rows()
    assert len(w) == 1 and w[0] == 1000 and within[0] == 0 and (mean == 1).all()


def test_weight_splits_only_where_the_limit_forces_it():
    assert copies_that_fit(10, 4, 2.0, 3.0, 8.0) == 4
    assert copies_that_fit(10, 4, 2.0, 1.0, 8.0) == 10
    assert copies_that_fit(7, 1, 0.0, 10.0, 1.0) == 0
    x, w = cloud(400, 3), np.random.default_rng(1).integers(1, 50, 400)
    t = SphereTree(40, 3)
    t.offer(x, w)
    mean, weight, _ = t.rows()
    assert weight.sum() == w.sum() and np.allclose((mean * weight[:, None]).sum(0), (x * w[:, None]).sum(0))


def test_features_stay_within_the_limit():
    t = SphereTree(50, 5, block=1)
    t.offer(cloud(2000, 5))
    assert (t.within[: t.n] <= t.limit * (1 + 1e-9)).all()


def test_snapshot_goes_on_where_it_was():
    x = cloud(2000, 4)
    a = SphereTree(50, 4, 2)
    a.offer(x)
    b = SphereTree(50, 4, 2)
    b.offer(x[:1024])
    b = SphereTree.restore(b.snapshot())
    b.offer(x[1024:])
    assert a.rows()[1].sum() == b.rows()[1].sum() and np.allclose(a.rows()[0], b.rows()[0])


@pytest.mark.parametrize("bad", [np.array([[np.nan, 1.0]]), np.array([[np.inf, 1.0]]), np.ones((2, 3))])
def test_bad_points_are_refused(bad):
    with pytest.raises(ValueError):
        SphereTree(5, 2).offer(bad)


@pytest.mark.parametrize("w", [[0], [-1], [1.5]])
def test_bad_weights_are_refused(w):
    with pytest.raises(ValueError):
        SphereTree(5, 2).offer(np.ones((1, 2)), np.array(w))


def test_tree_records():
    t = SphereTree(30, 2)
    t.offer(cloud(500, 2))
    rec = t.features()
    assert sum(r["w"] for r in rec) == 500 and all(r["parent_id"] < len(rec) for r in rec)
    assert all(r["depth"] == 0 if r["parent_id"] < 0 else r["depth"] == rec[r["parent_id"]]["depth"] + 1 for r in rec)


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 10**6), st.integers(1, 10**6), st.floats(0, 10), st.floats(0, 10), st.floats(0, 10))
def test_copies_never_pass_the_limit(w, s, c, d2, extra):
    limit = c + extra
    fit = copies_that_fit(w, s, c, d2, limit)
    assert 0 <= fit <= w
    assert c + (s * fit / (s + fit)) * d2 <= limit * (1 + 1e-9) + 1e-9


def test_baseline_kernels_keep_the_weight():
    x = cloud(800, 3)
    t = FeatureTree(60, 3)
    t.offer(x)
    assert t.rows()[1].sum() == 800 and len(t.rows()[1]) <= 60
    y, w = sampling_coreset(x, np.ones(800), 40, 1)
    assert w.sum() == 800 and len(w) <= 40


def test_sampled_cells_keep_weight_vector_sum_and_energy():
    rng = np.random.default_rng(4)
    x, w, within = cloud(5000, 3), rng.integers(1, 9, 5000).astype(float), rng.random(5000)
    y, c, inner = sampled_cells(x, w, 40, 1, within)
    assert len(c) <= 40 and c.sum() == w.sum()
    assert np.allclose(c @ y, w @ x)
    energy = lambda a, b, e: float((b * (a * a).sum(1)).sum() + e.sum())
    assert np.isclose(energy(y, c, inner), energy(x, w, within))


def test_sampled_cells_cost_no_more_than_one_center_on_flat_data():
    """Hardly clusterable points of 400 dimensions: centers made of drawn points cost more than the mean of all."""
    x, worse = np.random.default_rng(5).uniform(-1, 1, (600, 400)), 0
    one = float(((x - x.mean(0)) ** 2).sum())
    for seed in range(5):
        y, c, _ = sampled_cells(x, np.ones(600), 60, seed)
        worse += float(block_distances(x, kmeanspp_array(y, c.astype(float), 5, seed, 3)[0]).min(1).sum()) > one
    assert worse == 0


@pytest.mark.parametrize("m", [100, 190, 300])
def test_first_threshold_is_none_that_cannot_fit(m):
    """A feature goes only where another reference is within the top radius: as many gaps as must go lie within it."""
    x = cloud(400, 12)
    t = SphereTree(m, 12, block=400)
    limits, first = [], t._first_limit
    t._first_limit = lambda: limits.append(first()) or limits[-1]
    t.offer(x)
    d2 = ((x[:, None] - x[None]) ** 2).sum(2)
    np.fill_diagonal(d2, np.inf)
    assert (d2.min(1) <= limits[0] / 8 * (1 + 1e-9)).sum() >= 400 - (m - m // 16)
    assert len(limits) == 1 and t.rows()[1].sum() == 400 and t.n <= m


def test_a_block_is_compared_with_many_references_by_parts():
    """The product of a block and all top references is never held at once, nor copies of the block's own distances."""
    import tracemalloc

    t = SphereTree(4000, 32)
    t.offer(cloud(4000, 32))
    x = cloud(1024, 32, seed=1)
    tracemalloc.start()
    t._absorb(x, x, np.ones(1024, np.int64), np.zeros(1024), np.zeros(1024), split=True)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 1024 * 4000 * 8 and t.rows()[1].sum() == 5024


def test_full_features_take_no_part_in_the_sums(monkeypatch):
    """Points pass a feature that the nearest of them does not fit without any sum; those that fit elsewhere are joined."""
    t = SphereTree(8, 2)
    t.limit = 1.0
    t.open(np.zeros(2), np.zeros(2), 10, 1.0, -1)
    t.open(np.array([9.0, 0.0]), np.array([9.0, 0.0]), 10, 0.0, -1)
    x = np.array([[0.1, 0.0], [9.1, 0.0], [0.0, 0.2], [9.0, 0.1]])
    seen, join = [], SphereTree._join_nearest
    monkeypatch.setattr(SphereTree, "_join_nearest", lambda self, todo, *a: seen.append(todo.tolist()) or join(self, todo, *a))
    t.offer(x)
    assert sorted(seen[0]) == [1, 3] and t.w[:2].tolist() == [10, 12] and t.rows()[1].sum() == 24


def test_nearest_child_is_that_of_a_search_through_all():
    """Runs of points below nodes of no, one, few and many children."""
    t = SphereTree(400, 3)
    t.limit = 8.0
    for node, kids in ((0, 0), (1, 1), (2, 3), (3, 90)):
        t.open(np.full(3, float(node)), np.full(3, float(node)), 1, 0.0, -1)
    for node, kids in ((1, 1), (2, 3), (3, 90)):
        for p in cloud(kids, 3, seed=node):
            t.open(p, p, 1, 0.0, node)
    node = np.repeat([0, 1, 2, 3], [4, 5, 6, 40])
    x = cloud(55, 3, seed=7)
    best, d2 = t._nearest(x, node, 1)
    for i in range(55):
        at = t._children(int(node[i]))
        far = ((t.ref[at] - x[i]) ** 2).sum(1)
        assert best[i] == (at[far.argmin()] if len(at) else -1) and (d2[i] == np.inf if not len(at) else np.isclose(d2[i], far.min()))


@pytest.mark.parametrize("r2", [0.0, 0.05, 0.5, 40.0])
def test_leaders_are_the_same_from_a_list_of_pairs(r2):
    x = np.concatenate([cloud(150, 2), cloud(10, 2)])
    near = ((x[:, None] - x[None]) ** 2).sum(2) <= r2
    listed = SphereTree._lead_listed(x, near, r2)
    assert (listed == SphereTree._lead(x, near, r2)).all()
    assert (((x - x[listed]) ** 2).sum(1) <= r2).all() and not near[listed[:, None], listed[None]][listed[:, None] != listed[None]].any()
