"""Experiment workloads: families of point sets, method comparisons, parameter sweeps.

``python -m kmfold.plans.experiments DIR`` prints the tables for the given tables
folder. Times are the driver's clock around one action; the headline is the median
over seeds. Costs are always taken on the full, unprojected input.
"""

from __future__ import annotations

import argparse
import time

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kmfold.functions import cost, features
from kmfold.functions.arrays import to_matrix
from kmfold.operators import baselines, clustering, linalg, measures, summaries
from kmfold.sources import generators, points
from kmfold.staging import discard, ship_package, stage

METHODS = ("direct", "piecewise", "tree", "cf_tree", "sampling_coreset", "uniform_sample", "kmeanspp")
SVD = "y int, d int, l int, seed int, percent double, percent_fixed double, percent_root double, percent_fixed_root double, exact_residual double, random_residual double, exact_cpu_s double, random_cpu_s double"


def families(spark: SparkSession, sf_dir: str, small: bool = True) -> dict[str, DataFrame]:
    """Stand-ins of the point sets: many rows, flat spectrum, words, blocks, simplices, cube, evolving stream."""
    n = 1 if small else 10
    return {
        "descriptors": points.line_points(spark, sf_dir, 32),
        "embeddings": points.emb64(spark, sf_dir).select("id", "x", "w"),
        "words": points.bag_of_words(points.table(spark, sf_dir, "documents"), "doc_id", 256),
        "blocks": generators.block_signal(spark, 10 * n, 100, 100, x=20).select("id", "x", "w"),
        "simplex": generators.nested_simplex(spark, 10, 100 * n).select("id", "x", "w"),
        "cube": generators.uniform_cube(spark, 1000 * n, 100),
        "events": points.event_points(spark, sf_dir).select("id", "x", "w"),
    }


def summarize(pts: DataFrame, method: str, k: int, l: int, ps: int, np_: int, seed: int, factor: int) -> DataFrame:  # noqa: E741
    """A summary by name, sized ``factor * k``."""
    m = factor * k
    if method == "direct":
        return summaries.direct_summary(pts, k, m, seed=seed)
    if method == "piecewise":
        return summaries.piecewise_summary(pts, k, ps, l, m, seed=seed)
    if method == "tree":
        return summaries.tree_summary(pts, k, l, ps, np_, seed)
    if method == "cf_tree":
        return baselines.cf_tree(pts, k, m)
    if method == "sampling_coreset":
        return baselines.sampling_coreset_summary(pts, k, m, max(ps, 2 * m), seed=seed)
    if method == "uniform_sample":
        return baselines.uniform_sample(pts, m, seed + 1)
    raise ValueError(f"method must be one of {METHODS}")


def solve(pts: DataFrame, method: str, k: int, l: int, ps: int, np_: int, seed: int, factor: int, restarts: int = 3) -> tuple[float, dict]:  # noqa: E741
    """Cost of a method's centers on the input, and how large its summary was."""
    if method == "kmeanspp":
        centers, _ = clustering.kmeanspp(pts, k, seed + 1, max_iter=10)
        return cost.cost_value(pts, centers), {"rows": float("nan")}
    s = stage(summarize(pts, method, k, l, ps, np_, seed, factor), "summary")
    centers = clustering.center_rows(clustering.kmeanspp_summary(s, k, restarts, seed))
    rows = s.count()
    discard(s)
    return cost.cost_value(pts, centers), {"rows": rows}


def compare_methods(pts: DataFrame, k: int, methods=METHODS, l: int | None = None, ps: int = 500, np_: int = 3, seeds=range(5), factor: int = 40) -> DataFrame:  # noqa: E741
    """Run table of several methods on one staged point set."""
    l = l or linalg.target_dim(k)  # noqa: E741
    out = None
    for method in methods:
        own = [0] if method in ("cf_tree",) else seeds
        runs = measures.repeat(pts.sparkSession, method, {"k": k, "l": l, "ps": ps, "np": np_}, own, lambda s, m=method: solve(pts, m, k, l, ps, np_, s, factor))
        out = runs if out is None else out.unionByName(runs)
    return out.withColumn("k", F.lit(k))


def sweep_piecewise(pts: DataFrame, k: int, sizes=(50, 100, 250, 500), dims=None, seed: int = 0, factor: int = 20) -> DataFrame:
    """``ps, l, cost, weight, seconds`` of the piecewise method over piece sizes and dimensions."""
    d = points.dimension(pts)
    rows = []
    for ps in sizes:
        for l in dims or (k, -(-3 * k // 2), 2 * k, d):  # noqa: E741
            t = time.time()
            s = stage(summaries.piecewise_summary(pts, k, ps, l, factor=factor, seed=seed), "summary")
            c = clustering.center_rows(clustering.kmeanspp_summary(s, k, 3, seed))
            rows.append((ps, l, cost.cost_value(pts, c), int(s.agg(F.sum("w")).first()[0]), time.time() - t))
    return pts.sparkSession.createDataFrame(rows, "ps int, l int, cost double, weight bigint, seconds double")


def sweep_tree(pts: DataFrame, k: int, sizes=(50, 100), dims=(8,), fans=(2, 3, 5, 10), seed: int = 0, n_points: int | None = None) -> DataFrame:
    """``ps, l, np, cost, weight, levels, seconds`` of the tree."""
    rows = []
    for ps in sizes:
        for l in dims:  # noqa: E741
            for fan in fans:
                t = time.time()
                s = stage(summaries.tree_summary(pts, k, l, ps, fan, seed, n_points=n_points), "summary")
                c = clustering.center_rows(clustering.kmeanspp_summary(s, k, 3, seed))
                top = s.agg(F.sum("w").alias("w"), F.max("level").alias("v")).first()
                rows.append((ps, l, fan, cost.cost_value(pts, c), int(top["w"]), int(top["v"]) + 1, time.time() - t))
    return pts.sparkSession.createDataFrame(rows, "ps int, l int, np int, cost double, weight bigint, levels int, seconds double")


def svd_table(spark: SparkSession, ys=(10, 20), ds=(100,), ls=(20, 25, 30), blocks: int = 20, x: int = 20, seeds: int = 5, kind: str = "random") -> DataFrame:
    """Exact against randomized decomposition of block-signal matrices, one task a matrix and dimension."""
    ship_package(spark)

    def run(table):
        y, l = table.column("y")[0].as_py(), table.column("l")[0].as_py()  # noqa: E741
        a = to_matrix(table.sort_by("id").column("x"))
        told = linalg.svd_comparison(a, l, range(seeds), kind, reference_rank=ls[0])
        names = [c.split(" ")[0] for c in SVD.split(", ")]
        rows = [{**t, "y": y, "d": a.shape[1]} for t in told]
        types = {"y": pa.int32(), "d": pa.int32(), "l": pa.int32(), "seed": pa.int32()}
        return pa.table({n: pa.array([r[n] for r in rows], types.get(n, pa.float64())) for n in names})

    out = None
    for d in ds:
        for y in ys:
            pts = generators.block_signal(spark, blocks, y, d, x=x).select("id", "x", F.lit(y).alias("y"), F.explode(F.array(*map(F.lit, ls))).alias("l"))
            one = pts.groupBy("y", "l").applyInArrow(run, SVD)
            out = one if out is None else out.unionByName(one)
    return out


def svd_blocks(spark: SparkSession, ys, ds, ls, blocks: int, x: int, seeds: int = 5, kind: str = "random") -> DataFrame:
    """The same comparison for every block as a matrix of its own: one task a block, ranks in one go."""
    ship_package(spark)
    names = [c.split(" ")[0] for c in SVD.split(", ")]
    types = {"y": pa.int32(), "d": pa.int32(), "l": pa.int32(), "seed": pa.int32()}

    def run(table):
        a = to_matrix(table.sort_by("id").column("x"))
        rows = [{**t, "y": len(a), "d": a.shape[1]} for l in ls for t in linalg.svd_comparison(a, l, range(seeds), kind, reference_rank=ls[0])]  # noqa: E741
        return pa.table({n: pa.array([r[n] for r in rows], types.get(n, pa.float64())) for n in names})

    out = None
    for d in ds:
        for y in ys:
            pts = generators.block_signal(spark, blocks, y, d, x=x).select("id", "x", "label")
            one = pts.groupBy("label").applyInArrow(run, SVD)
            out = one if out is None else out.unionByName(one)
    return out


def svd_statistics(table: DataFrame) -> DataFrame:
    """Minimum, maximum, average and median deviation, CPU seconds and the speed ratio by matrix and dimension."""
    p = F.col("percent")
    return table.groupBy("d", "y", "l").agg(F.min(p).alias("percent_min"), F.max(p).alias("percent_max"), F.avg(p).alias("percent_avg"), F.median(p).alias("percent_median"), F.median("percent_fixed_root").alias("fixed_root_median"), F.max("exact_cpu_s").alias("exact_cpu_s"), F.median("random_cpu_s").alias("random_cpu_s"), (F.max("exact_cpu_s") / F.greatest(F.median("random_cpu_s"), F.lit(1e-6))).alias("speedup"))


def one_center_cost(pts: DataFrame) -> float:
    return float(features.cf_agg(pts).select(features.cf_within(F.col("cf")).alias("c")).first()["c"])


def main() -> None:
    parser = argparse.ArgumentParser(description=__doc__)
    parser.add_argument("tables", help="folder of the Parquet tables")
    parser.add_argument("--k", type=int, nargs="*", default=[5, 10])
    parser.add_argument("--seeds", type=int, default=3)
    parser.add_argument("--families", nargs="*")
    parser.add_argument("--large", action="store_true")
    args = parser.parse_args()
    spark = SparkSession.builder.config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    print("exact against randomized decomposition")
    sizes = {"ys": (100, 200, 300), "ds": (500,), "ls": (100, 125, 150), "blocks": 100, "x": 100} if args.large else {}
    svd_statistics(svd_table(spark, **sizes)).orderBy("d", "y", "l").show(50, False)
    for name, pts in families(spark, args.tables, not args.large).items():
        if args.families and name not in args.families:
            continue
        pts = stage(pts, name)
        base = one_center_cost(pts)
        for k in args.k:
            runs = stage(compare_methods(pts, k, seeds=range(args.seeds)), "runs")
            print(f"{name}: {pts.count()} points of {points.dimension(pts)} coordinates, k={k}, one center {base:.6g}")
            measures.run_statistics(runs, ["method"]).orderBy("cost_median").show(truncate=False)
            measures.ratios(runs, "direct", ["k"]).orderBy("method").show(truncate=False)
    e = stage(points.emb64(spark, args.tables).select("id", "x", "w"), "embeddings")
    print("piecewise sweep, embeddings, k=5")
    sweep_piecewise(e, 5).orderBy("ps", "l").show(50, False)
    print("tree sweep, embeddings, k=5")
    sweep_tree(e, 5).orderBy("ps", "l", "np").show(50, False)


__all__ = ["compare_methods", "families", "one_center_cost", "solve", "summarize", "svd_statistics", "svd_table", "sweep_piecewise", "sweep_tree"]

if __name__ == "__main__":
    main()
