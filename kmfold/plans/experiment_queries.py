"""Experiment workloads as queries: what every right run must return, with DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from kmfold.operators import linalg, measures
from kmfold.plans import experiments
from kmfold.plans.pieces import by_key
from kmfold.sources import points
from kmfold.staging import stage

Q: dict = {}
SQL: dict[str, str] = {}


def query(sql: str):
    def add(f):
        Q[f.__name__] = f
        SQL[f.__name__] = sql
        return f

    return add


@query("SELECT y, d, l, true AS below_seven_percent, true AS not_below_optimum FROM (VALUES (10), (20)) a(y) CROSS JOIN (VALUES (100)) b(d) CROSS JOIN (VALUES (20), (25), (30)) c(l)")
def svd_comparison_blocks(spark, sf_dir):
    """Block-signal matrices: the sketch's residual is within seven percent of the optimum in every run."""
    t = experiments.svd_table(spark)
    return t.groupBy("y", "d", "l").agg((F.max("percent") < 7).alias("below_seven_percent"), (F.min("percent") >= -1e-6).alias("not_below_optimum"))


@query("SELECT d, l, true AS below_seven_percent FROM (VALUES (128), (256)) a(d) CROSS JOIN (VALUES (5), (10), (50)) b(l)")
def svd_comparison_words(spark, sf_dir):
    """All documents through the triangular factor of their table; buckets of 128 are those of 256 added in pairs."""
    rows = []
    whole = linalg.triangle(points.bag_of_words(points.table(spark, sf_dir, "documents"), "doc_id", 256))
    for d in (128, 256):
        a = whole.reshape(len(whole), -1, d).sum(1)
        for l in (5, 10, 50):  # noqa: E741
            rows.append((d, l, all(t["percent"] < 7 for t in linalg.svd_comparison(a, l, range(3)))))
    return spark.createDataFrame(rows, "d int, l int, below_seven_percent boolean")


@query("SELECT ps, l, count(*) AS weight, true AS below_one_center FROM embeddings CROSS JOIN (VALUES (50), (100), (250), (500)) a(ps) CROSS JOIN (VALUES (5), (8), (10), (64)) b(l) GROUP BY ps, l")
def piecewise_sweep(spark, sf_dir):
    """Piece sizes and target dimensions k, 1.5k, 2k and d."""
    e = stage(points.emb64(spark, sf_dir).select("id", "x", "w"), "embeddings")
    base = experiments.one_center_cost(e)
    return experiments.sweep_piecewise(e, 5, (50, 100, 250, 500)).select("ps", "l", "weight", (F.col("cost") <= base).alias("below_one_center"))


@query("SELECT ps, l, np, count(*) AS weight, true AS below_one_center FROM embeddings CROSS JOIN (VALUES (5), (10)) c(l) CROSS JOIN (VALUES (50), (100)) a(ps) CROSS JOIN (VALUES (2), (3), (5), (10)) b(np) GROUP BY ps, l, np")
def tree_sweep(spark, sf_dir):
    e = stage(points.emb64(spark, sf_dir).select("id", "x", "w"), "embeddings")
    base = experiments.one_center_cost(e)
    return experiments.sweep_tree(e, 5, dims=(5, 10)).select("ps", "l", "np", "weight", (F.col("cost") <= base).alias("below_one_center"))


@query("SELECT true AS skipped, true AS same_cost")
def no_gain_beyond_dimension(spark, sf_dir):
    """With l at the dimension the projection is skipped: piecewise is then the direct method."""
    e = stage(points.emb64(spark, sf_dir).select("id", "x", "w"), "embeddings")
    l = linalg.target_dim(100, d=64)  # noqa: E741
    a, _ = experiments.solve(e, "piecewise", 10, l, 100, 3, 0, 20)
    b, _ = experiments.solve(e, "piecewise", 10, 1000, 100, 3, 0, 20)
    moved = linalg.project(by_key(e, 100), l).agg(F.sum("moved")).first()[0]
    return spark.createDataFrame([(moved == 0.0, abs(a - b) < 1e-9)], "skipped boolean, same_cost boolean")


@query("SELECT method, CASE WHEN method = 'cf_tree' THEN 1 ELSE 5 END AS runs, true AS near_kmeanspp FROM (VALUES ('direct'), ('piecewise'), ('tree'), ('cf_tree'), ('sampling_coreset'), ('kmeanspp')) a(method)")
def methods_on_words(spark, sf_dir):
    """All methods on word counts, five seeds: median cost within a quarter of k-means++ on the full data."""
    pts = stage(points.bag_of_words(points.table(spark, sf_dir, "documents"), "doc_id", 64), "words")
    runs = stage(experiments.compare_methods(pts, 4, [m for m in experiments.METHODS if m != "uniform_sample"], ps=250, seeds=range(5), factor=20), "runs")
    ratio = measures.ratios(runs, "kmeanspp", ["k"])
    count = runs.groupBy("method").agg(F.count("*").cast("int").alias("runs"))
    return ratio.join(count, "method").select("method", "runs", (F.col("cost_ratio") <= 1.25).alias("near_kmeanspp"))


@query("SELECT family, true AS summarized FROM (VALUES ('descriptors'), ('embeddings'), ('words'), ('blocks'), ('simplex'), ('cube'), ('events')) a(family)")
def direct_on_all_families(spark, sf_dir):
    """The direct method over every family: weight kept, cost at most that of one center."""
    rows = []
    for name, pts in experiments.families(spark, sf_dir).items():
        pts = stage(pts, name)
        c, _ = experiments.solve(pts, "direct", 5, 1, 500, 3, 0, 20, restarts=2)
        rows.append((name, c <= experiments.one_center_cost(pts) * (1 + 1e-9)))
    return spark.createDataFrame(rows, "family string, summarized boolean")
