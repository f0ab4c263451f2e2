"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))
os.environ.setdefault("OMP_NUM_THREADS", "1")
os.environ.setdefault("OPENBLAS_NUM_THREADS", "1")

from pyspark.sql import SparkSession  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench")
        .config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "12g"))
        .config("spark.ui.enabled", "false").config("spark.driver.host", "127.0.0.1").config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.execution.arrow.maxRecordsPerBatch", "20000").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from kmfold.functions import cost, features
    from kmfold.operators import baselines, clustering, linalg, summaries
    from kmfold.plans import experiments
    from kmfold.plans.catalog import QUERIES, flagship
    from kmfold.sources import generators, points
    from kmfold.staging import stage

    took: dict[str, float] = {}
    notes: dict[str, float] = {}

    def timed(name, f):
        t = time.time()
        out = f()
        took[name] = round(time.time() - t, 3)
        print(name, took[name], file=sys.stderr, flush=True)
        return out

    n = int(CPUS)
    line = timed("load_line64", lambda: stage(points.line_points(spark, SF_DIR, 64).repartition(2 * n), "line64"))
    emb = stage(points.emb64(spark, SF_DIR).select("id", "x", "w").repartition(n), "emb64")
    total = line.count()
    notes["rows_line64"] = total
    base = {}
    for k in (10, 50):
        made = {
            "direct": lambda: summaries.direct_summary(line, k, factor=40),
            "piecewise": lambda: summaries.piecewise_summary(line, k, 2000, linalg.target_dim(k, d=64), factor=40),
            "tree": lambda: summaries.tree_summary(line, k, linalg.target_dim(k, d=64), 40 * k, 16, n_points=total),
        }
        for name, f in made.items():
            s = timed(f"{name}_line64_k{k}", lambda: stage(f(), "summary"))
            c = clustering.center_rows(clustering.kmeanspp_summary(s, k, 3))
            notes[f"cost_{name}_line64_k{k}"] = base[name, k] = cost.cost_value(line, c)
    # the summary size that the published times stand for: 200 points a center
    for name, f in {"direct": lambda: summaries.direct_summary(line, 50), "piecewise": lambda: summaries.piecewise_summary(line, 50, 10_000, 50), "tree": lambda: summaries.tree_summary(line, 50, 50, 10_000, 10, n_points=total)}.items():
        s = timed(f"{name}_line64_k50_m10000", lambda: stage(f(), "summary"))
        notes[f"cost_{name}_line64_k50_m10000"] = cost.cost_value(line, clustering.center_rows(clustering.kmeanspp_summary(s, 50, 1)))
    _, history = timed("kmeanspp_full_line64_k10", lambda: clustering.kmeanspp(line, 10, max_iter=5))
    notes["cost_kmeanspp_full_line64_k10"] = history[-1]
    for name, f in {"cf_tree": lambda: baselines.cf_tree(emb, 10, 400), "sampling_coreset": lambda: baselines.sampling_coreset_summary(emb, 10, 400), "tree": lambda: summaries.tree_summary(emb, 10, 15, 400, 3, n_points=emb.count())}.items():
        timed(f"{name}_emb64_k10", lambda: stage(f(), "summary"))
    timed("cf_line64", lambda: features.cf_agg(line).collect())
    timed("cost_line64_k50", lambda: cost.cost_value(line, clustering.uniform_seeds(line, 50)))
    timed("spectrum_line64", lambda: linalg.spectrum(line).collect())
    table = timed("svd_10000x500", lambda: experiments.svd_statistics(experiments.svd_table(spark, (100,), (500,), (100,), 100, 100, 2)).collect())
    notes["svd_exact_cpu_s"], notes["svd_random_cpu_s"], notes["svd_percent_max"] = table[0]["exact_cpu_s"], table[0]["random_cpu_s"], table[0]["percent_max"]
    blocks = stage(generators.block_signal(spark, 100, 100, 500), "blocks")
    for name, f in {"direct": lambda: summaries.direct_summary(blocks, 10, factor=40), "tree": lambda: summaries.tree_summary(blocks, 10, 15, 400, 5, n_points=10000)}.items():
        s = timed(f"{name}_blocks_10000x500_k10", lambda: stage(f(), "summary"))
        notes[f"cost_{name}_blocks_10000x500_k10"] = cost.cost_value(blocks, clustering.center_rows(clustering.kmeanspp_summary(s, 10, 1)))
    timed("flagship", lambda: flagship(spark, SF_DIR).collect())
    for name in ("dense_index_counts", "join_sort_merge", "aggregate_hash", "join_asof", "window_ranking", "doc_term_counts"):
        timed(name, lambda: QUERIES[name](spark, SF_DIR).write.format("noop").mode("overwrite").save())
    try:
        from kmfold.llm.queries import QUERIES as LLM
    except ImportError:
        LLM = {}
    for name, f in LLM.items():
        timed(name, lambda: f(spark, SF_DIR).write.format("noop").mode("overwrite").save())
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": float(Path(SF_DIR).name.removeprefix("sf") or 0) if Path(SF_DIR).name.startswith("sf") else SF_DIR, "notes": {k: float(v) for k, v in notes.items()}}))
    spark.stop()


if __name__ == "__main__":
    main()
