"""Direct, piecewise and tree summaries on tables: equivalences, limits, quality."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from kmfold.functions import cost, features
from kmfold.operators import baselines, clustering, measures, summaries
from kmfold.plans import pieces
from kmfold.plans.pieces import TreeParams
from kmfold.sources import generators, points
from kmfold.staging import stage


def rows(df):
    return sorted((tuple(round(v, 9) for v in r["x"]), r["w"]) for r in df.collect())


def test_no_projection_is_the_direct_method(spark, sf):
    e = points.emb64(spark, sf)
    a = summaries.direct_summary(e, 5, factor=10, mode="single")
    b = summaries.piecewise_summary(e, 5, ps=4096, l=8, svd="none", factor=10, mode="single")
    assert rows(a) == rows(b)


def test_one_node_tree_is_the_piecewise_method(spark, sf):
    e = points.emb64(spark, sf)
    a = summaries.tree_summary(e, 5, l=64, ps=500, np=4)
    assert a.agg(F.sum("w")).first()[0] == 500 and a.select("node").distinct().count() == 1


def test_same_seed_same_rows_for_any_partitioning(spark, sf):
    e = points.emb64(spark, sf)
    assert rows(summaries.tree_summary(e, 5, l=8, ps=50, np=3)) == rows(summaries.tree_summary(e.repartition(9), 5, l=8, ps=50, np=3))


def test_levels_and_counts():
    assert [lv["nodes"] for lv in pieces.plan_levels(500, TreeParams(l=8, ps=50, np=3))] == [4, 2, 1]
    assert pieces.tree_counts(45, TreeParams(l=2, ps=5, np=3)) == {"levels": 2, "svds": 12, "runs": 4, "reductions_per_point": 2}
    assert [lv["nodes"] for lv in pieces.plan_levels(500, TreeParams(l=8, ps=50, np=[10, 3]))] == [1]
    assert [lv["nodes"] for lv in pieces.plan_levels(550, TreeParams(l=8, ps=50, np=3, flush="merge"))] == [3, 1]
    with pytest.raises(ValueError):
        TreeParams(l=0, ps=5)


def test_degenerate_inputs(spark):
    one = spark.createDataFrame([(0, [1.0, 2.0], 1)], "id bigint, x array<double>, w bigint")
    assert rows(summaries.tree_summary(one, 3, l=1, ps=5)) == [((1.0, 2.0), 1)]
    zeros = spark.range(40).select("id", F.array(F.lit(0.0), F.lit(0.0)).alias("x"), F.lit(2).cast("bigint").alias("w"))
    s = summaries.tree_summary(zeros, 2, l=1, ps=10, np=2)
    assert s.agg(F.sum("w")).first()[0] == 80
    assert summaries.tree_summary(zeros.limit(0), 2, l=1, ps=10).count() == 0
    assert summaries.direct_summary(zeros.limit(0), 2).count() == 0
    assert clustering.kmeanspp_summary(s, 5, restarts=1).count() == 1  # fewer centers than asked where points are equal


def test_invalid_points_are_refused_or_dropped(spark):
    bad = spark.createDataFrame([(0, [1.0, float("nan")], 1.0), (1, [1.0, 2.0], 1.0), (2, None, 1.0), (3, [1.0, 1.0], 0.0), (4, [1.0, 1.0], 1.5)], "id bigint, x array<double>, w double")
    assert [r["id"] for r in points.points_from(bad, "id", "x", "w", "drop").collect()] == [1]
    with pytest.raises(Exception, match="positive whole number"):
        points.points_from(bad, "id", "x", "w").collect()
    ragged = spark.createDataFrame([(0, [1.0]), (1, [1.0, 2.0])], "id bigint, x array<double>")
    with pytest.raises(ValueError):
        points.dimension(ragged)


def test_weighted_input_equals_premerged_copies(spark, sf):
    q = points.quantity_weighted(spark, sf).limit(200)
    q = stage(q, "q")
    again = points.premerge(points.replicated(q))
    a, b = features.cf_agg(q).first()["cf"], features.cf_agg(again).first()["cf"]
    assert a["w"] == b["w"] and np.allclose(a["ls"], b["ls"])
    m = features.cf_agg(points.multiplied(q)).first()["cf"]
    assert m["w"] != a["w"]


def test_quality_of_summaries_on_clustered_data(spark):
    pts = stage(generators.block_signal(spark, 8, 150, 48, x=20), "blocks")
    _, full = clustering.kmeanspp(pts, 8, max_iter=8)
    for s in (summaries.direct_summary(pts, 8, factor=40), summaries.piecewise_summary(pts, 8, 300, 12, factor=40), summaries.tree_summary(pts, 8, l=12, ps=300, np=2)):
        c = clustering.center_rows(clustering.kmeanspp_summary(stage(s, "s"), 8, restarts=5))
        assert cost.cost_value(pts, c) <= 1.15 * full[-1]


def test_worst_case_family_is_solved(spark):
    pts = stage(generators.nested_simplex(spark, 5, 200), "simplex")
    s = summaries.tree_summary(pts, 5, l=10, ps=60, np=3)
    c = clustering.center_rows(clustering.kmeanspp_summary(stage(s, "s"), 5, restarts=5))
    assert cost.cost_value(pts, c) <= 1.05 * generators.simplex_optimum(5, 200)


def test_certificate_holds_for_every_level_variant(spark, sf):
    e = points.emb64(spark, sf)
    for levels in ("all", "leaf", "none"):
        full = stage(summaries.tree_full(e, TreeParams(l=10, ps=50, np=3, project_levels=levels), keep_levels=True), "full")
        top = full.agg(F.max("level")).first()[0]
        dev = measures.coreset_deviation(e, full.filter(F.col("level") == top), measures.center_panel(e, 4, 8)).collect()
        bound = summaries.total_error(full)
        assert all(abs(r["input_cost"] ** 0.5 - r["summary_cost"] ** 0.5) <= bound * (1 + 1e-9) for r in dev)


def test_single_mode_refuses_long_streams(spark, sf, monkeypatch):
    monkeypatch.setattr(summaries, "SINGLE_ROWS", 100)
    with pytest.raises(ValueError, match="sharded"):
        summaries.direct_summary(points.emb64(spark, sf), 5, mode="single")


def test_brute_force_bounds_kmeanspp():
    x = np.random.default_rng(0).standard_normal((9, 2))
    best = baselines.brute_force(x, 2)
    _, found = clustering.kmeanspp_array(x, np.ones(9), 2, 1, restarts=20)
    assert best <= found * (1 + 1e-9) and found <= 1.3 * best


def test_plan_has_one_exchange_a_level(spark, sf):
    e = points.emb64(spark, sf)
    s = summaries.tree_summary(e, 5, l=8, ps=50, np=3, n_points=500)
    plan = s._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 3
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan


def test_scan_reads_the_vector_column_only(spark, sf):
    d = points.table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("x")).filter("id >= 10")
    plan = cost.kmeans_cost(d, [(0, [0.0] * 64)])._jdf.queryExecution().executedPlan().toString()
    assert "label" not in plan.split("ReadSchema")[1] and "GreaterThanOrEqual(vec_id,10)" in plan


def test_memory_guard_and_advice():
    with pytest.raises(ValueError):
        measures.check_memory(10, k=5, d=5, ps=10, n=100, b=2)
    assert summaries.choose(10**9, 1000, 50) == "tree" and summaries.choose(10**4, 64, 5) == "direct"


def test_more_centers_than_the_bound_are_refused(spark, monkeypatch):
    from kmfold.functions import cost

    monkeypatch.setattr(cost, "BROADCAST_COORDINATES", 640)
    centers = spark.createDataFrame([(i, [float(i), 0.0]) for i in range(11)], "cid int, c array<double>")
    assert len(cost.center_list(centers.filter("cid < 10"))) == 10
    with pytest.raises(ValueError, match="too many centers"):
        cost.center_list(centers)


@pytest.mark.parametrize("parts", [1, 3, 8])
def test_sums_are_kept_through_every_reduction(spark, sf, parts):
    from kmfold.operators import baselines

    e = points.emb64(spark, sf).repartition(parts)
    x = points.matrix(e)
    made = {
        "direct": summaries.direct_summary(e, 5, factor=12),
        "tree": summaries.tree_summary(e, 5, l=64, ps=60, project_levels="none"),
        "merge_reduce": summaries.merge_reduce(e, 5, ps=60),
        "union": summaries.reduce_summary(summaries.union_summaries(summaries.direct_summary(e.filter("id % 2 = 0"), 5, m=40), summaries.direct_summary(e.filter("id % 2 = 1"), 5, m=40)), 5, m=50),
        "cf_tree": baselines.cf_tree(e, 5, m=60),
        "chain": baselines.chain_reduce(e, 5, 100, m=60),
    }
    for name, s in made.items():
        got = measures.conservation(s).first()
        rows = s.select("x", "w").collect()
        assert got["weight"] == len(x) and got["size"] <= 60, name
        assert np.isclose(got["ss"], (x**2).sum()), name
        assert np.allclose(sum(r["w"] * np.array(r["x"]) for r in rows), x.sum(0)), name


def test_inner_costs_move_with_copies_and_do_not_count_against_the_threshold():
    from kmfold.operators.sphere import SphereTree

    rng = np.random.default_rng(2)
    x, w, c = rng.standard_normal((500, 3)), rng.integers(1, 20, 500), rng.random(500) * 9
    for block in (1, 128):
        a, b = SphereTree(40, 3, block=block), SphereTree(40, 3, block=block)
        a.offer(x, w)
        b.offer(x, w, c)
        assert (a.rows()[1] == b.rows()[1]).all() and np.allclose(a.rows()[0], b.rows()[0])
        assert np.isclose(b.rows()[2].sum(), a.rows()[2].sum() + c.sum()) and np.isclose(b.merged(), a.merged())


def test_tree_over_any_ids(spark, sf):
    e = points.emb64(spark, sf).select("id", "x", "w")
    plain = summaries.tree_summary(e, 5, l=8, ps=50).collect()
    for other in (e.withColumn("id", F.col("id") * 1_000_003 + 17), e.withColumn("id", F.col("id") + 5000), e.withColumn("id", -F.col("id"))):
        rows = summaries.tree_summary(other, 5, l=8, ps=50).collect()
        assert {r["node"] for r in rows} == {0} and len(rows) <= 50 and sum(r["w"] for r in rows) == 500
    assert sorted(r["w"] for r in plain) == sorted(r["w"] for r in summaries.tree_summary(e.withColumn("id", F.col("id") * 7), 5, l=8, ps=50).collect())
    with pytest.raises(ValueError):
        summaries.tree_summary(e, 5, l=8, ps=50, n_points=400)


def test_the_race_draws_in_proportion_to_the_distances(spark):
    from kmfold.operators import clustering

    rng = np.random.default_rng(0)
    x = rng.standard_normal((400, 2)) + 12 * rng.standard_normal((6, 2))[rng.integers(0, 6, 400)]
    pts = spark.createDataFrame([(i, v, 1 + i % 3) for i, v in enumerate(x.tolist())], "id bigint, x array<double>, w bigint").repartition(3)
    for candidates in (8, 4096):
        seeds = np.array([c for _, c in clustering.race_seeds(pts, 12, 3, candidates)])
        if candidates == 8:
            few = seeds
    assert seeds.shape == (12, 2) and (few == seeds).all()  # the number of scans changes nothing
    # the whole race by brute force: every clock to its end
    clock = rng.exponential(size=400)
    w = 1.0 + np.arange(400) % 3
    chosen, times = [0], [0.0]
    spent = np.zeros(400)
    for _ in range(11):
        rate = w * ((x[:, None] - x[chosen][None]) ** 2).sum(2).min(1)
        with np.errstate(divide="ignore"):
            left = np.where(rate > 0, (clock - spent) / rate, np.inf)
        ends, now = clustering.clock_ends(x, w, clock, x[chosen], np.array(times))
        assert np.allclose(ends[rate > 0], times[-1] + left[rate > 0]) and np.allclose(now, rate)
        i = int(left.argmin())
        spent += rate * left[i]
        chosen.append(i)
        times.append(times[-1] + left[i])
    # the first draw: how often each point wins is its share of the cost
    cost = w * ((x - x[0]) ** 2).sum(1)
    wins = np.bincount([int(clustering.clock_ends(x, w, rng.exponential(size=400), x[[0]], np.array([0.0]))[0].argmin()) for _ in range(4000)], minlength=400)
    assert np.abs(wins / 4000 - cost / cost.sum()).max() < 0.02


def test_one_lloyd_step_is_the_plain_one(spark, sf):
    from kmfold.operators import clustering

    e = points.emb64(spark, sf).withColumn("w", F.pmod("id", F.lit(4)) + 1).repartition(3)
    x, w = points.matrix(e), np.arange(500) % 4 + 1
    centers = [*((10 + i, x[i].tolist()) for i in range(6)), (99, [50.0] * 64)]
    moved, cost = clustering.lloyd_step(e, centers)
    c = np.array([v for _, v in centers])
    d2 = ((x[:, None] - c[None]) ** 2).sum(2)
    near = d2.argmin(1)
    assert np.isclose(cost, (w * d2.min(1)).sum()) and [i for i, _ in moved] == [i for i, _ in centers] and moved[-1][1] == centers[-1][1]
    for k in range(6):
        assert np.allclose(moved[k][1], np.average(x[near == k], axis=0, weights=w[near == k]))


def test_the_feature_tree_is_balanced():
    from kmfold.operators.sphere import FeatureTree

    x = np.random.default_rng(5).standard_normal((3000, 3))
    t = FeatureTree(400, 3, branching=6)
    t.offer(x)
    depths, todo = set(), [(t.root, 1)]
    while todo:
        page, depth = todo.pop()
        assert 0 < page.n <= 6 or page is t.root
        if page.below is None:
            depths.add(depth)
        else:
            assert len(page.below) == page.n
            for i, below in enumerate(page.below):
                mean, w, within = below.sums()
                assert np.allclose(page.mean[i], mean) and np.isclose(page.w[i], w) and np.isclose(page.within[i], within)
                todo.append((below, depth + 1))
    assert depths == {t.height} and t.height > 2
    mean, w, within = t.rows()
    assert w.sum() == 3000 and np.isclose((w * (mean**2).sum(1)).sum() + within.sum(), (x**2).sum())


def test_one_scan_costs_several_summaries(spark, sf, monkeypatch):
    from kmfold.plans.comparison_queries import cost_of, costs_of
    from kmfold.staging import stage

    e = stage(points.emb64(spark, sf).select("id", "x", "w"), "embeddings")
    made = [(k, stage(summaries.direct_summary(e, k, factor=10), "summary")) for k in (3, 5)]
    each = [cost_of(e, s, k, range(1)) for k, s in made]
    scans, once = [], cost.panel_costs
    monkeypatch.setattr(cost, "panel_costs", lambda *a: scans.append(1) or once(*a))
    assert costs_of(e, made) == pytest.approx(each, rel=1e-12) and len(scans) == 1
