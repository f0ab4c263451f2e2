"""Comparisons of methods and variants by cost on the full input, as queries with DuckDB SQL.

Every truth value is measured on the table at hand; weights and sums are those of the
summaries, held against the input's by SQL.
"""

from __future__ import annotations

import statistics

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kmfold.functions import cost, features
from kmfold.functions.vectors import squared_length
from kmfold.operators import baselines, clustering, linalg, measures, summaries
from kmfold.plans import experiments, pieces
from kmfold.plans.method_queries import DIM, grid, long, matrices
from kmfold.plans.pieces import TreeParams
from kmfold.sources import generators, points
from kmfold.staging import stage

Q: dict = {}
SQL: dict[str, str] = {}


def query(sql: str):
    def add(f):
        Q[f.__name__] = f
        SQL[f.__name__] = sql
        return f

    return add


def cost_of(pts: DataFrame, summary: DataFrame, k: int, seeds=range(5), how: str = "d2") -> float:
    """Median over seeds of the cost on the input of the best of three restarts on a summary."""
    s = stage(summary, "summary")
    return statistics.median(cost.cost_value(pts, clustering.center_rows(clustering.kmeanspp_summary(s, k, 3, seed, how))) for seed in seeds)


def costs_of(pts: DataFrame, made: list[tuple[int, DataFrame]], seed: int = 0) -> list[float]:
    """Costs on the input of the best of three restarts on each staged summary (its k beside it): one scan for all."""
    panel = [(i, clustering.center_rows(clustering.kmeanspp_summary(s, k, 3, seed))) for i, (k, s) in enumerate(made)]
    told = {r["panel"]: r["cost"] for r in cost.panel_costs(pts, panel).collect()}
    return [float(told[i]) for i, _ in panel]


# --- sums kept, on any partitioning and any ids ---------------------------------------------------


@query(f"WITH {DIM}, s AS (SELECT count(*) // 64 AS w, CAST(sum(v) AS BIGINT) AS ls, CAST(sum(v * v) AS BIGINT) AS ss FROM dim) SELECT method, w, ls, ss, true AS small FROM s CROSS JOIN (VALUES ('direct'), ('tree'), ('merge_reduce'), ('chain'), ('cf_tree')) m(method)")
def sums_over_partitions(spark, sf_dir):
    """Weight, vector sum and energy of summaries made from eight partitions: nothing is lost on the way up."""
    g = stage(grid(spark, sf_dir).repartition(8), "grid")
    made = {
        "direct": summaries.direct_summary(g, 5, m=70), "tree": summaries.tree_summary(g, 5, l=64, ps=70, project_levels="none"),
        "merge_reduce": summaries.merge_reduce(g, 5, ps=70), "chain": baselines.chain_reduce(g, 5, 100, m=70), "cf_tree": baselines.cf_tree(g, 5, m=70),
    }
    out = None
    for name, s in made.items():
        s = stage(s, name)
        total = s.agg(F.sum(F.aggregate(F.transform("x", lambda v: v * F.col("w")), F.lit(0.0), lambda a, v: a + v)).alias("ls"))
        r = measures.conservation(s).crossJoin(total).select(F.lit(name).alias("method"), F.col("weight").alias("w"), long(F.col("ls")).alias("ls"), long(F.col("ss")).alias("ss"), (F.col("size") <= 70).alias("small"))
        out = r if out is None else out.unionByName(r)
    return out


@query("SELECT ids, 1 AS roots, count(*) AS w, true AS small FROM embeddings CROSS JOIN (VALUES ('dense'), ('spread'), ('shifted'), ('negative')) v(ids) GROUP BY ids")
def tree_over_any_ids(spark, sf_dir):
    """Ids with gaps, away from 0 or below it: one root with all the weight."""
    e, out = points.emb64(spark, sf_dir), None
    for name, key in {"dense": F.col("id"), "spread": F.col("id") * 1_000_003, "shifted": F.col("id") + 77_777, "negative": -F.col("id")}.items():
        s = summaries.tree_summary(e.withColumn("id", key), 5, l=8, ps=50)
        r = s.agg(F.countDistinct("node").cast("int").alias("roots"), F.sum("w").alias("w"), (F.count("*") <= 50).alias("small")).withColumn("ids", F.lit(name))
        out = r if out is None else out.unionByName(r)
    return out


@query("SELECT count(*) AS n, true AS full_pieces, true AS none_larger FROM embeddings")
def pieces_in_split(spark, sf_dir):
    """Pieces counted inside each partition: no exchange, one short piece a partition at most."""
    e = stage(points.emb64(spark, sf_dir).repartition(3), "embeddings")
    g = pieces.in_split(e, 40).groupBy("piece").agg(F.count("*").alias("m"))
    return g.agg(F.sum("m").alias("n"), (F.count_if(F.col("m") < 40) <= 3).alias("full_pieces"), (F.max("m") <= 40).alias("none_larger"))


@query("SELECT count(*) AS n, 6 AS coordinates, true AS same_rows, true AS basis_differs FROM embeddings")
def projection_coordinates(spark, sf_dir):
    """Coordinates and basis of each piece rebuild the projected rows; bases of different pieces differ."""
    e = pieces.by_key(points.emb64(spark, sf_dir), 100)
    c = linalg.project(e, 6, kind="exact", emit="coords")
    back = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda j: F.aggregate(F.sequence(F.lit(0), F.lit(5)), F.lit(0.0), lambda s, i: s + F.element_at("x", i + 1) * F.element_at("basis", i * 64 + j + 1)))
    rows = linalg.project(e, 6, kind="exact").select("id", F.col("x").alias("y"))
    both = c.withColumn("back", back).join(rows, "id")
    off = F.aggregate(F.zip_with("back", "y", lambda a, b: F.abs(a - b)), F.lit(0.0), lambda s, v: F.greatest(s, v))
    told = both.agg(F.count("*").alias("n"), F.max(F.size("x")).alias("coordinates"), (F.max(off) < 1e-9).alias("same_rows"))
    bases = c.groupBy("piece").agg(F.first("basis").alias("basis")).agg((F.count_distinct("basis") == F.count("*")).alias("basis_differs"))
    return told.crossJoin(bases)


# --- methods against one another -------------------------------------------------------------------


@query("SELECT k, method, count(*) AS weight, true AS near_direct, true AS falls FROM lineitem CROSS JOIN (VALUES (5), (10), (50), (100)) a(k) CROSS JOIN (VALUES ('direct'), ('piecewise'), ('tree')) b(method) GROUP BY k, method")
def descriptors_methods_by_k(spark, sf_dir):
    """Many rows of 32 coordinates, k below and above them: all methods within a tenth of the direct one, costs fall with k."""
    pts = stage(points.line_points(spark, sf_dir, 32), "descriptors")
    weight, made = {}, []
    for k in (5, 10, 50, 100):
        for method in ("direct", "piecewise", "tree"):
            s = stage(experiments.summarize(pts, method, k, linalg.target_dim(k, d=32), 1000 if method == "piecewise" else 40 * k, 8, 0, 40), "summary")
            weight[k, method] = int(s.agg(F.sum("w")).first()[0])
            made.append((k, s))
    rows, last, base = [], {}, {}
    for (k, method), c in zip(weight, costs_of(pts, made)):
        base.setdefault(k, c)
        rows.append((k, method, weight[k, method], c <= 1.1 * base[k], c <= last.get(method, float("inf"))))
        last[method] = c
    return spark.createDataFrame(rows, "k int, method string, weight bigint, near_direct boolean, falls boolean")


@query("SELECT k, method, 1000 AS weight, true AS near_direct FROM (VALUES (5), (10)) a(k) CROSS JOIN (VALUES ('direct'), ('piecewise'), ('tree'), ('sampling_coreset'), ('uniform_sample')) b(method)")
def block_signal_methods(spark, sf_dir):
    """Ten blocks of 100 rows in 500 dimensions, 100 of them signal: hardly clusterable, all methods within three percent."""
    pts = stage(generators.block_signal(spark, 10, 100, 500).select("id", "x", "w"), "blocks")
    rows = []
    for k in (5, 10):
        base = None
        for method in ("direct", "piecewise", "tree", "sampling_coreset", "uniform_sample"):
            s = stage(experiments.summarize(pts, method, k, linalg.target_dim(k), 100, 3, 0, 20), "summary")
            c = cost_of(pts, s, k, range(2))
            base = base or c
            rows.append((k, method, int(s.agg(F.sum("w")).first()[0]), c <= 1.03 * base))
    return spark.createDataFrame(rows, "k int, method string, weight int, near_direct boolean")


@query("SELECT k, method, 600 AS weight, true AS near_direct, true AS below_one_center FROM (VALUES (10), (20), (50)) a(k) CROSS JOIN (VALUES ('direct'), ('piecewise'), ('tree')) b(method)")
def uniform_cube_methods(spark, sf_dir):
    """Nothing to find in a cube: all methods cost nearly what one center costs, and never more."""
    pts = stage(generators.uniform_cube(spark, 600, 100), "cube")
    one, rows = experiments.one_center_cost(pts), []
    for k in (10, 20, 50):
        base = None
        for method in ("direct", "piecewise", "tree"):
            s = stage(experiments.summarize(pts, method, k, linalg.target_dim(k), 200 if method == "piecewise" else 4 * k, 3, 0, 4), "summary")
            c = cost_of(pts, s, k, range(1))
            base = base or c
            rows.append((k, method, int(s.agg(F.sum("w")).first()[0]), c <= 1.05 * base, c <= one * (1 + 1e-9)))
    return spark.createDataFrame(rows, "k int, method string, weight int, near_direct boolean, below_one_center boolean")


@query("SELECT k, n, method, k AS clusters, true AS optimum_reached FROM (VALUES (10, 1000), (5, 400)) a(k, n) CROSS JOIN (VALUES ('direct'), ('piecewise'), ('tree')) b(method)")
def nested_simplex_methods(spark, sf_dir):
    """Every method finds the nested simplices: cost within five percent of the closed form."""
    rows = []
    for k, n in ((10, 1000), (5, 400)):
        pts = stage(generators.nested_simplex(spark, k, n), "simplex")
        for method in ("direct", "piecewise", "tree"):
            s = stage(experiments.summarize(pts, method, k, 2 * k, 100, 3, 0, 20), "summary")
            centers = clustering.center_rows(clustering.kmeanspp_summary(s, k, 5))
            rows.append((k, n, method, len(centers), cost.cost_value(pts, centers) <= 1.05 * generators.simplex_optimum(k, n)))
    return spark.createDataFrame(rows, "k int, n int, method string, clusters int, optimum_reached boolean")


@query("SELECT t.source, m.method, t.n AS weight, true AS near_direct FROM (SELECT 'conversations' AS source, count(*) AS n FROM conversations UNION ALL SELECT 'pages', count(*) FROM pages UNION ALL SELECT 'benchmark', count(*) FROM benchmark UNION ALL SELECT 'documents', count(*) FROM documents) t CROSS JOIN (VALUES ('direct'), ('piecewise'), ('tree')) m(method)")
def words_of_all_tables(spark, sf_dir):
    """Word counts of every text table (pages without their tags), k = 4: all methods within a tenth of the direct one."""
    t = lambda name: points.table(spark, sf_dir, name)
    numbered = pieces.dense_index(t("conversations").select("conv_id", "turn", "role", "text"), ["conv_id", "turn", "role", "text"])
    sources = {
        "conversations": points.bag_of_words(numbered, "id", 64), "documents": points.bag_of_words(t("documents"), "doc_id", 64), "benchmark": points.bag_of_words(t("benchmark"), "item_id", 64),
        "pages": points.bag_of_words(t("pages").select("page_id", F.regexp_replace(F.col("html"), "(?s)<[^>]*>", " ").alias("text")), "page_id", 64),
    }
    rows = []
    for name, pts in sources.items():
        pts, base = stage(pts, name), None
        for method in ("direct", "piecewise", "tree"):
            s = stage(experiments.summarize(pts, method, 4, 8, 160 if method == "tree" else 250, 3, 0, 40), "summary")
            c = cost_of(pts, s, 4, range(2))
            base = base if base is not None else c
            rows.append((name, method, int(s.agg(F.sum("w")).first()[0]), c <= 1.1 * base))
    return spark.createDataFrame(rows, "source string, method string, weight bigint, near_direct boolean")


@query("SELECT method, true AS near_kmeanspp FROM (VALUES ('cf_tree'), ('sampling_coreset'), ('chain'), ('coupled_tree'), ('running_subspace'), ('uniform_sample'), ('project_then_cluster'), ('global_projection')) v(method)")
def baseline_costs(spark, sf_dir):
    """Every baseline by the cost of its centers on the full input, against k-means++ on all points (five seeds each)."""
    e = stage(points.emb64(spark, sf_dir).select("id", "x", "w"), "embeddings")
    full = statistics.median(clustering.kmeanspp(e, 5, seed, max_iter=10)[1][-1] for seed in range(1, 6))
    made = {
        "cf_tree": baselines.cf_tree(e, 5, m=100), "sampling_coreset": baselines.sampling_coreset_summary(e, 5, m=100, ps=200), "chain": baselines.chain_reduce(e, 5, 100, m=100),
        "coupled_tree": baselines.coupled_tree(e, 5, 8, 100), "running_subspace": baselines.running_subspace(e, 5, 8, 100, m=100), "uniform_sample": baselines.uniform_sample(e, 100),
    }
    got = {name: cost_of(e, s, 5) for name, s in made.items()}
    got["project_then_cluster"] = cost.cost_value(e, baselines.project_then_cluster(e, 5, 8, 100)[0])
    got["global_projection"] = cost.cost_value(e, baselines.global_projection(e, 5, 8)[0])
    return spark.createDataFrame([(name, c <= 1.15 * full) for name, c in got.items()], "method string, near_kmeanspp boolean")


@query("SELECT method, 5 AS runs, true AS timed, true AS ratio_near_one FROM (VALUES ('direct'), ('piecewise'), ('tree')) v(method)")
def measured_ratios(spark, sf_dir):
    """Five seeds of every method through the run table: statistics, and ratios to the direct method, of measured runs."""
    e = stage(points.emb64(spark, sf_dir).select("id", "x", "w"), "embeddings")
    runs = stage(experiments.compare_methods(e, 5, ("direct", "piecewise", "tree"), ps=100, seeds=range(5), factor=20), "runs")
    told = measures.run_statistics(runs, ["method"]).join(measures.ratios(runs, "direct", ["k"]), "method").join(runs.groupBy("method").agg(F.count("*").cast("int").alias("runs")), "method")
    ordered = (F.col("cost_min") <= F.col("cost_median")) & (F.col("cost_median") <= F.col("cost_max")) & (F.col("seconds_min") > 0) & (F.col("speedup") > 0)
    return told.select("method", "runs", ordered.alias("timed"), F.col("cost_ratio").between(0.9, 1.1).alias("ratio_near_one"))


# --- variants --------------------------------------------------------------------------------------


@query("SELECT n, least(100, 10 * n // 100) AS one_summarizer, least(100, 3 * 10) AS tree_node FROM (VALUES (300), (600), (1200)) v(n)")
def rank_as_the_stream_grows(spark, sf_dir):
    """Directions that one summarizer meets grow with the pieces fed to it; a node of the tree meets three pieces' only."""
    rows = []
    for n in (300, 600, 1200):
        pts = generators.uniform_cube(spark, n, 100)
        fed = linalg.project(pieces.by_key(pts, 100), 10)
        node = stage(fed.withColumn("node", F.expr("piece div 3")), "nodes")
        each = [measures.intrinsic_dim(node.filter(F.col("node") == r["node"])) for r in node.select("node").distinct().collect()]
        rows.append((n, measures.intrinsic_dim(fed), max(each)))
    return spark.createDataFrame(rows, "n int, one_summarizer int, tree_node int")


@query("SELECT n, method, n AS weight, true AS near_direct FROM (VALUES (1000), (2000), (4000)) a(n) CROSS JOIN (VALUES ('direct'), ('piecewise'), ('tree')) b(method)")
def growing_block_signal(spark, sf_dir):
    """Growing streams of block signal, one repetition: one summarizer fed by many pieces, and the tree, as good as the direct method."""
    rows = []
    for n in (1000, 2000, 4000):
        pts, base = stage(generators.block_signal(spark, 10, n // 10, 200, x=50).select("id", "x", "w"), "blocks"), None
        for method in ("direct", "piecewise", "tree"):
            s = stage(summaries.piecewise_summary(pts, 10, 200, 15, m=200, mode="single") if method == "piecewise" else experiments.summarize(pts, method, 10, 15, 200, 3, 0, 20), "summary")
            c = cost_of(pts, s, 10, range(1))
            base = base or c
            rows.append((n, method, int(s.agg(F.sum("w")).first()[0]), c <= 1.03 * base))
    return spark.createDataFrame(rows, "n int, method string, weight int, near_direct boolean")


@query("""WITH n AS (SELECT CAST(ceil(count(*) / 100.0) AS BIGINT) AS p FROM embeddings),
t AS (WITH RECURSIVE lv(variant, fan, pieces) AS (SELECT 'coupled', 2, CAST(p AS BIGINT) FROM n UNION ALL SELECT variant, fan, CAST(ceil(pieces / fan) AS BIGINT) FROM lv WHERE pieces > 1)
  SELECT variant, CAST(sum(pieces) + max(pieces) AS BIGINT) - 1 AS svds, CAST(sum(pieces) AS BIGINT) AS runs FROM lv GROUP BY variant),
d AS (WITH RECURSIVE lv(pieces, nodes) AS (SELECT CAST(p AS BIGINT), CAST(ceil(p / 3.0) AS BIGINT) FROM n UNION ALL SELECT nodes, CAST(ceil(nodes / 3.0) AS BIGINT) FROM lv WHERE nodes > 1)
  SELECT 'decoupled' AS variant, CAST(sum(pieces) AS BIGINT) AS svds, CAST(sum(nodes) AS BIGINT) AS runs FROM lv)
SELECT variant, svds, runs, true AS near FROM (SELECT variant, svds, runs FROM t UNION ALL SELECT variant, svds, runs FROM d)""")
def coupled_against_decoupled(spark, sf_dir):
    """One decomposition for each summarizer run against three: counted runs and decompositions, and their costs."""
    e = stage(points.emb64(spark, sf_dir).select("id", "x", "w"), "embeddings")
    rows, base = [], None
    for variant, fan in (("coupled", [1, 2]), ("decoupled", 3)):
        params = TreeParams(l=8, ps=100, np=fan)
        full = stage(summaries.tree_full(e, params, keep_levels=True), "levels")
        told = summaries.node_counters(full).agg(F.sum("svds").alias("svds"), F.count("*").alias("runs")).first()
        top = full.agg(F.max("level")).first()[0]
        c = cost_of(e, full.filter(F.col("level") == top).select(*summaries.SUMMARY_COLUMNS), 5)
        base = base or c
        rows.append((variant, told["svds"], told["runs"], 0.9 <= c / base <= 1.1))
    return spark.createDataFrame(rows, "variant string, svds bigint, runs bigint, near boolean")


@query("SELECT method, count(*) AS weight, true AS near_direct FROM embeddings CROSS JOIN (VALUES ('chain'), ('binary_tree'), ('wide_tree')) v(method) GROUP BY method")
def chain_and_tree_costs(spark, sf_dir):
    """Repeated reduction in a chain and in trees against one summarizer: costs within a tenth, five seeds."""
    e = stage(points.emb64(spark, sf_dir).select("id", "x", "w"), "embeddings")
    base = cost_of(e, summaries.direct_summary(e, 5, m=100), 5)
    made = {"chain": baselines.chain_reduce(e, 5, 100, m=100), "binary_tree": summaries.merge_reduce(e, 5, ps=100), "wide_tree": summaries.tree_summary(e, 5, l=64, ps=100, np=5, project_levels="none")}
    rows = [(name, int(s.agg(F.sum("w")).first()[0]), cost_of(e, s, 5) <= 1.1 * base) for name, s in made.items()]
    return spark.createDataFrame(rows, "method string, weight bigint, near_direct boolean")


@query("SELECT levels, true AS near FROM (VALUES ('all'), ('leaf'), ('none')) v(levels)")
def projection_level_costs(spark, sf_dir):
    """Projection on every level, on leaves only, or never: costs within a tenth of one another."""
    e = stage(points.emb64(spark, sf_dir).select("id", "x", "w"), "embeddings")
    got = {levels: cost_of(e, summaries.tree_summary(e, 5, l=8, ps=100, np=3, project_levels=levels), 5) for levels in ("all", "leaf", "none")}
    return spark.createDataFrame([(levels, c <= 1.1 * min(got.values())) for levels, c in got.items()], "levels string, near boolean")


@query("SELECT finder, block, true AS near FROM (VALUES ('full', 1), ('band', 1), ('auto', 256), ('auto', 1024)) v(finder, block)")
def insertion_costs(spark, sf_dir):
    """Points one by one or in blocks, by either finder: costs within a twentieth."""
    e = stage(points.emb64(spark, sf_dir).select("id", "x", "w"), "embeddings")
    got = {(f, b): cost_of(e, summaries.direct_summary(e, 5, m=100, finder=f, block=b), 5) for f, b in (("full", 1), ("band", 1), ("auto", 256), ("auto", 1024))}
    return spark.createDataFrame([(f, b, c <= 1.05 * min(got.values())) for (f, b), c in got.items()], "finder string, block int, near boolean")


@query("SELECT 'd2' AS seeding, true AS cheaper, true AS cheaper_after_lloyd")
def seeding_costs(spark, sf_dir):
    """On nested simplices of unequal sizes squared-distance seeds cost less than uniform ones, before and after Lloyd (medians of 15 seeds)."""
    pts = generators.nested_simplex(spark, 10, 500).filter("label < 2 OR id < 100")
    s = stage(summaries.direct_summary(pieces.dense_index(pts.select("id", "x", "w"), ["id"], "place").withColumn("id", F.col("place")).drop("place"), 10, factor=20), "summary")
    rows = s.select("x", "w").collect()
    x, w = np.array([r["x"] for r in rows]), np.array([r["w"] for r in rows], float)
    order = np.lexsort(tuple(x.T[::-1]))
    x, w = x[order], w[order]
    start, end = {}, {}
    for how in ("d2", "uniform"):
        seeds = [clustering.seed_array(x, w, 10, np.random.default_rng([5, i]), how) for i in range(15)]
        start[how] = statistics.median(float((w * clustering.block_distances(x, c).min(1)).sum()) for c in seeds)
        end[how] = statistics.median(clustering.lloyd_array(x, w, c)[1] for c in seeds)
    return spark.createDataFrame([("d2", start["d2"] < start["uniform"], end["d2"] < end["uniform"])], "seeding string, cheaper boolean, cheaper_after_lloyd boolean")


@query("SELECT two_sided, true AS power_helps, true AS oversampling_helps, true AS close FROM (VALUES (false), (true)) v(two_sided)")
def sketch_sweep(spark, sf_dir):
    """Deviation of the sketch from the optimum over power steps 0 to 2 and oversampling 0 to 20 (medians of five seeds)."""
    rows = {two: [] for two in (False, True)}
    for a in matrices(points.emb64(spark, sf_dir)):
        _, s, _ = np.linalg.svd(a, full_matrices=False)
        own = float((s[10:] ** 2).sum())
        for two in rows:
            off = {(p, o): statistics.median(100 * (linalg.residual(a, linalg.svd_random(a, 10, seed, o, p, two)[1]) - own) / own for seed in range(5)) for p in (0, 1, 2) for o in (0, 5, 10, 20)}
            power = all(off[p, o] >= off[p + 1, o] - 1e-9 for p in (0, 1) for o in (0, 5, 10, 20))
            over = all(off[p, 0] >= off[p, 20] - 1e-9 for p in (0, 1, 2))
            rows[two].append((power, over, 0 <= off[2, 10] < 7))
    return spark.createDataFrame([(two, *map(all, zip(*told))) for two, told in rows.items()], "two_sided boolean, power_helps boolean, oversampling_helps boolean, close boolean")


@query("SELECT factor, count(*) AS weight, true AS near_kmeanspp FROM embeddings CROSS JOIN (VALUES (4), (20), (80)) v(factor) GROUP BY factor")
def summary_size_sweep(spark, sf_dir):
    """Summaries of 4, 20 and 80 points a center: costs within a fifth, a tenth and a twentieth of k-means++ on all points."""
    e = stage(points.emb64(spark, sf_dir).select("id", "x", "w"), "embeddings")
    full = statistics.median(clustering.kmeanspp(e, 5, seed, max_iter=10)[1][-1] for seed in range(1, 6))
    rows = []
    for factor, most in ((4, 1.2), (20, 1.1), (80, 1.05)):
        s = stage(summaries.direct_summary(e, 5, factor=factor), "summary")
        rows.append((factor, int(s.agg(F.sum("w")).first()[0]), cost_of(e, s, 5) <= most * full))
    return spark.createDataFrame(rows, "factor int, weight bigint, near_kmeanspp boolean")


@query("SELECT y, d, l, 500 AS runs, true AS not_below_optimum, true AS below_seven_percent, true AS random_faster FROM (VALUES (100)) a(y) CROSS JOIN (VALUES (500)) b(d) CROSS JOIN (VALUES (100), (125), (150)) c(l)")
def svd_comparison_grid(spark, sf_dir):
    """A hundred block-signal matrices of 100 rows, each alone: five seeds, CPU seconds of both decompositions."""
    t = experiments.svd_blocks(spark, (100,), (500,), (20, 25, 30), 100, 100)
    named = t.withColumn("l", F.col("l") * 5)  # a fifth of the rank that one matrix of all blocks is given
    told = named.groupBy("y", "d", "l").agg(F.count("*").cast("int").alias("runs"), (F.min("percent") >= -1e-6).alias("not_below_optimum"), (F.median("percent") < 7).alias("below_seven_percent"), (F.sum("random_cpu_s") < F.sum("exact_cpu_s") * 5).alias("random_faster"))
    return told


@query("SELECT count(*) AS n, true AS energy_kept FROM embeddings")
def weighted_energy(spark, sf_dir):
    """Energy of weighted points before and after a reduction of the weighted summary."""
    e = grid(spark, sf_dir).withColumn("w", F.pmod("id", F.lit(5)) + 1).repartition(4)
    total = e.agg(F.sum(F.col("w") * squared_length("x"))).first()[0]
    s = stage(summaries.direct_summary(e, 5, m=60, weight_col="w"), "summary")
    got = measures.conservation(s).first()
    n = features.cf_agg(e).select("cf.w").first()[0]
    return e.agg(F.count("*").alias("n"), F.lit(bool(abs(got["ss"] - total) <= 1e-9 * total and got["weight"] == n)).alias("energy_kept"))
