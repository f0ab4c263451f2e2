"""Cost and accuracy measures, run tables and their statistics."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kmfold.functions.cost import cost_value, panel_costs
from kmfold.operators.linalg import gram_matrix

RUNS = "method string, params map<string,string>, seed bigint, cost double, seconds double, counters map<string,double>"


def coreset_deviation(pts: DataFrame, summary: DataFrame, panel: list[tuple[int, list]]) -> DataFrame:
    """``panel, input_cost, summary_cost, deviation`` for several center sets, one scan of each side."""
    a = panel_costs(pts, panel).withColumnRenamed("cost", "input_cost")
    b = panel_costs(summary, panel).withColumnRenamed("cost", "summary_cost")
    return a.join(b, "panel").withColumn("deviation", F.when(F.col("input_cost") > 0, F.abs(F.col("summary_cost") - F.col("input_cost")) / F.col("input_cost")).otherwise(F.lit(0.0)))


def center_panel(pts: DataFrame, k: int, sets: int = 20, seed: int = 7) -> list[tuple[int, list]]:
    """Center sets of all kinds: random rows, one center, far away, and spread copies of a row."""
    rows = [list(map(float, r["x"])) for r in pts.select("x").orderBy("id").limit(max(sets * k, 50)).collect()]
    rng = np.random.default_rng(seed)
    panel = []
    for p in range(sets):
        pick = [rows[i] for i in rng.choice(len(rows), min(k, len(rows)), replace=False)]
        if p % 5 == 1:
            pick = pick[:1]
        elif p % 5 == 2:
            pick = [[v + 100.0 for v in c] for c in pick]
        elif p % 5 == 3:
            pick = [[v + float(e) for v, e in zip(c, rng.standard_normal(len(c)))] for c in pick]
        panel.append((p, list(enumerate(pick))))
    return panel


def conservation(summary: DataFrame) -> DataFrame:
    """Total weight, vector sum and sum of squared lengths that a summary stands for, and its size."""
    within = F.col("ss_within") if "ss_within" in summary.columns else F.lit(0.0)
    sq = F.aggregate("x", F.lit(0.0), lambda s, v: s + v * v)
    return summary.agg(F.count("*").alias("size"), F.sum("w").alias("weight"), F.sum(F.col("w") * sq + within).alias("ss"))


def intrinsic_dim(pts: DataFrame, tol: float = 1e-6) -> int:
    """Rank of a table's Gram matrix."""
    val = np.linalg.eigvalsh(gram_matrix(pts))
    return int((val > tol * max(val.max(), 1e-300)).sum()) if len(val) else 0


def memory_model(k: int, d: int, ps: int, n: int, b: int, factor: int = 200) -> dict:
    """Bytes a task holds: one piece, one decomposition, one summarizer (piecewise) or one a level (single-machine tree)."""
    m = factor * k
    piece, feature = 8 * ps * d, 8 * m * (2 * d + 6)
    levels = max(1, int(np.ceil(np.log(max(n / ps, 2)) / np.log(b))))
    return {"piece_bytes": piece, "svd_bytes": 3 * piece, "summary_bytes": feature, "levels": levels, "task_bytes": 4 * piece + feature, "tree_bytes": 4 * piece + levels * feature}


def check_memory(limit_bytes: int, **model) -> dict:
    """Refuse a plan whose tasks would not fit."""
    told = memory_model(**model)
    if told["task_bytes"] > limit_bytes:
        raise ValueError(f"a task needs {told['task_bytes']} bytes: lower ps or the summary factor")
    return told


def repeat(spark: SparkSession, method: str, params: dict, seeds: Iterable[int], once: Callable[[int], tuple[float, dict]]) -> DataFrame:
    """Run ``once(seed) -> (cost, counters)`` for each seed and time it by the driver's clock."""
    rows = []
    for seed in seeds:
        t = time.time()
        cost, counters = once(seed)
        rows.append((method, {k: str(v) for k, v in params.items()}, int(seed), float(cost), time.time() - t, {k: float(v) for k, v in counters.items()}))
    return spark.createDataFrame(rows, RUNS)


def run_statistics(runs: DataFrame, by: list[str]) -> DataFrame:
    """Minimum, maximum, average and median of cost and seconds of each group of runs."""
    out = []
    for c in ("cost", "seconds"):
        out += [F.min(c).alias(f"{c}_min"), F.max(c).alias(f"{c}_max"), F.avg(c).alias(f"{c}_avg"), F.median(c).alias(f"{c}_median")]
    return runs.groupBy(*by).agg(*out)


def ratios(runs: DataFrame, baseline: str, by: list[str]) -> DataFrame:
    """Median cost and seconds of every method over those of a baseline with the same parameters."""
    told = run_statistics(runs, ["method", *by]).select("method", *by, "cost_median", "seconds_median")
    base = told.filter(F.col("method") == baseline).select(*by, F.col("cost_median").alias("_c"), F.col("seconds_median").alias("_s"))
    return told.join(base, by).select("method", *by, (F.col("cost_median") / F.col("_c")).alias("cost_ratio"), (F.col("_s") / F.col("seconds_median")).alias("speedup"))


def quality(pts: DataFrame, centers: list, baseline_cost: float) -> float:
    """Cost of centers on the full input over a baseline's."""
    return cost_value(pts, centers) / baseline_cost
