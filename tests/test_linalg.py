"""Decompositions, projections and their weighted forms."""

import numpy as np
import pytest

from kmfold.operators import linalg
from kmfold.plans import pieces
from kmfold.sources import generators, points


def skewed(n=400, d=40, seed=0):
    rng = np.random.default_rng(seed)
    return rng.standard_normal((n, d)) * (0.8 ** np.arange(d))


@pytest.mark.parametrize("kind", ["gram", "random", "random2"])
def test_sketch_is_near_and_never_below_the_optimum(kind):
    x = skewed()
    for l in (5, 10, 20):
        told = linalg.svd_comparison(x, l, range(5), kind, reference_rank=5)
        assert all(-1e-6 <= t["percent"] < 7 for t in told)
    assert min(t["percent_fixed"] for t in told) < 0  # a fixed reference rank can be beaten


@pytest.mark.parametrize("kind", ["exact", "gram", "random", "random2"])
def test_projection_is_a_projection(kind):
    x = skewed()
    y, moved = linalg.project_matrix(x, 8, kind=kind)
    z, again = linalg.project_matrix(y, 8, kind=kind)
    assert np.linalg.matrix_rank(y, tol=1e-8) == 8 and np.allclose(y, z, atol=1e-6) and again < 1e-6
    assert np.isclose(moved, ((x - y) ** 2).sum())


def test_weights_act_as_copies():
    x, w = skewed(60, 10), np.arange(60) % 4 + 1
    y, _ = linalg.project_matrix(x, 3, w, "exact")
    z, _ = linalg.project_matrix(np.repeat(x, w, axis=0), 3, kind="exact")
    assert np.allclose(np.repeat(y, w, axis=0), z)
    m, _ = linalg.project_matrix(x * w[:, None], 3, kind="exact")
    assert not np.allclose(m / w[:, None], y, atol=1e-3)


def test_nothing_is_computed_where_nothing_can_be_gained():
    x = skewed(20, 10)
    assert linalg.project_matrix(x, 10)[0] is x and linalg.project_matrix(x, 50)[0] is x


def test_small_values_do_not_suffer_from_squaring():
    x = skewed(100, 12) * np.array([1.0] * 6 + [1e-9] * 6)
    s, v = linalg.svd_truncated(x, 10)
    assert np.allclose(s, np.linalg.svd(x, compute_uv=False)[:10], rtol=1e-6) and np.allclose(v @ v.T, np.eye(len(v)), atol=1e-8)


def test_target_dimension():
    assert linalg.target_dim(10) == 15 and linalg.target_dim(10, rule="k") == 10 and linalg.target_dim(10, eps=0.5, rule="k/eps") == 20
    assert linalg.target_dim(100, d=64) == 64
    with pytest.raises(ValueError):
        linalg.target_dim(10, rule="k/eps")


def test_project_by_piece_is_the_same_for_any_partitioning(spark, sf):
    e = pieces.by_key(points.emb64(spark, sf), 100)
    a = linalg.project(e, 6).select("id", "x").orderBy("id").collect()
    b = linalg.project(e.repartition(7), 6).select("id", "x").orderBy("id").collect()
    assert a == b and len(a) == 500


def test_coordinates_rebuild_the_projection(spark, sf):
    e = pieces.by_key(points.emb64(spark, sf), 250)
    c = {r["id"]: r for r in linalg.project(e, 6, kind="exact", emit="coords").collect()}
    p = {r["id"]: r["x"] for r in linalg.project(e, 6, kind="exact").collect()}
    for i in (0, 249, 250, 499):
        assert len(c[i]["x"]) == 6
        assert np.allclose(np.array(c[i]["x"]) @ np.array(c[i]["basis"]).reshape(6, -1), p[i])


def test_spectra_tell_the_families_apart(spark):
    share = {}
    for name, pts in {"cube": generators.uniform_cube(spark, 400, 40), "simplex": generators.nested_simplex(spark, 5, 50), "blocks": generators.block_signal(spark, 2, 100, 40, x=8)}.items():
        share[name] = linalg.spectrum(pts, 10).orderBy("rank").collect()[-1]["energy_cum"]
    assert share["simplex"] > share["blocks"] > share["cube"]


def test_triangle_stands_for_the_whole_table(spark):
    a = np.random.default_rng(4).standard_normal((700, 12)) * np.arange(1, 13)
    pts = spark.createDataFrame([(i, [float(v) for v in x], 1) for i, x in enumerate(a)], "id bigint, x array<double>, w bigint").repartition(5)
    r = linalg.triangle(pts)
    assert r.shape == (12, 12)
    for want, got in zip(linalg.svd_comparison(a, 2, range(3)), linalg.svd_comparison(r, 2, range(3))):
        for key in ("exact_residual", "random_residual", "percent"):
            assert abs(want[key] - got[key]) <= 1e-9 * max(1.0, abs(want[key]))


def test_words_are_not_collected(spark, sf, monkeypatch):
    from kmfold.plans import catalog

    def refuse(*_):
        raise AssertionError("all rows on the driver")

    seen, compare = {}, linalg.svd_comparison
    whole = {d: points.matrix(points.bag_of_words(points.table(spark, sf, "documents"), "doc_id", d)) for d in (128, 256)}
    monkeypatch.setattr(points, "matrix", refuse)
    monkeypatch.setattr(linalg, "svd_comparison", lambda a, l, s: seen.setdefault((a.shape[1], l), compare(a, l, s)))
    assert all(r["below_seven_percent"] for r in catalog.QUERIES["svd_comparison_words"](spark, sf).collect())
    for (d, l), told in seen.items():
        for want, got in zip(compare(whole[d], l, range(3)), told):
            assert abs(want["random_residual"] - got["random_residual"]) <= 1e-6 * want["random_residual"]
    assert len(seen) == 6
