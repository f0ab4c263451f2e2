"""Methods that the summaries are compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kmfold.functions.hashing import arithmetic_hash
from kmfold.functions.arrays import to_column, to_matrix
from kmfold.operators import clustering, linalg
from kmfold.operators.sphere import FeatureTree, SphereTree, sampled_cells, sampling_coreset
from kmfold.operators.summaries import FACTOR, SINGLE_ROWS, SUMMARY, SUMMARY_COLUMNS, points, run_iter, tree_full
from kmfold.plans.pieces import TreeParams
from kmfold.staging import ship_package, stage


def _summary_batch(level: int, node: int, x: np.ndarray, w: np.ndarray, within: np.ndarray | None = None) -> pa.RecordBatch:
    n = len(w)
    return pa.RecordBatch.from_pydict({"level": pa.array(np.full(n, level), pa.int32()), "node": pa.array(np.full(n, node), pa.int64()), "id": pa.array(np.arange(n), pa.int64()), "x": to_column(x), "w": pa.array(w, pa.int64()), "ss_within": pa.array(np.zeros(n) if within is None else within)})


def cf_tree(pts: DataFrame, k: int, m: int | None = None, threshold: float = 0.0, branching: int = 50, fan: int = 4) -> DataFrame:
    """Fast one-pass summary: one feature tree a partition, in the order of ids inside it, then a tree of them.

    No point moves; a partition is read batch by batch. Entries carry their inner costs.
    """
    spark = pts.sparkSession
    ship_package(spark)
    m = m or FACTOR * k

    def leaf(batches):
        from pyspark import TaskContext

        tree = None
        for b in batches:
            if b.num_rows:
                x = to_matrix(b.column(1))
                tree = tree or FeatureTree(m, x.shape[1], threshold, branching)
                tree.offer(x, b.column(2).to_numpy())
        if tree is not None:
            yield _summary_batch(0, TaskContext.get().partitionId(), *tree.rows())

    def join(level):
        def run(key, batches):
            t = pa.Table.from_batches(list(batches)).sort_by([("node", "ascending"), ("id", "ascending")])
            x = to_matrix(t.column("x"))
            tree = FeatureTree(m, x.shape[1], threshold, branching)
            tree.offer(x, t.column("w").to_numpy(), t.column("ss_within").to_numpy())
            yield _summary_batch(level, int(key[0].as_py()), *tree.rows())

        return run

    out = stage(points(pts).sortWithinPartitions("id").mapInArrow(leaf, SUMMARY), "feature_trees")
    nodes, level = (out.agg(F.max("node")).first()[0] or 0) + 1, 1
    while nodes > 1:
        out = out.withColumn("up", F.expr(f"node div {fan}")).select("up", "node", "id", "x", "w", "ss_within").groupBy("up").applyInArrow(run_iter(join(level)), SUMMARY)
        nodes, level = -(-nodes // fan), level + 1
        if level % 4 == 0 and nodes > 1:
            out = stage(out, f"feature_trees{level}")
    return out


def sampling_coreset_summary(pts: DataFrame, k: int, m: int | None = None, ps: int | None = None, fan_in: int = 2, seed: int = 0, stand: str = "centroid") -> DataFrame:
    """Stream coreset: representatives by squared-distance sampling for each piece, merged and reduced in a tree.

    A representative stands at the ``centroid`` of what it represents and carries its inner
    cost, or (``point``, the published form) where it was drawn.
    """
    if stand not in ("centroid", "point"):
        raise ValueError("stand must be centroid or point")
    spark = pts.sparkSession
    ship_package(spark)
    m = m or FACTOR * k
    ps = ps or 2 * m
    rows = points(pts)
    n = rows.count()

    def reduce(level):
        def run(key, batches):
            t = pa.Table.from_batches(list(batches)).sort_by([("node", "ascending"), ("id", "ascending")])
            name = int(key[0].as_py())
            x, w, own = to_matrix(t.column("x")), t.column("w").to_numpy().astype(float), [seed, level, name]
            made = sampling_coreset(x, w, m, own) if stand == "point" else sampled_cells(x, w, m, own, t.column("ss_within").to_numpy())
            yield _summary_batch(level, name, *made)

        return run

    ends = rows.agg(F.min("id").alias("low"), F.max("id").alias("high")).first()
    if n and ends["high"] - ends["low"] + 1 != n:
        raise ValueError("ids without gaps are needed: number the points first")
    out = rows.withColumn("id", F.col("id") - F.lit(ends["low"])).withColumn("node", F.lit(0).cast("bigint")).withColumn("up", F.expr(f"id div {ps}")).withColumn("ss_within", F.lit(0.0))
    out = out.select("up", "node", "id", "x", "w", "ss_within").groupBy("up").applyInArrow(run_iter(reduce(0)), SUMMARY)
    nodes, level = -(-n // ps), 1
    while nodes > 1:
        out = out.withColumn("up", F.floor(F.col("node") / fan_in).cast("bigint")).select("up", "node", "id", "x", "w", "ss_within").groupBy("up").applyInArrow(run_iter(reduce(level)), SUMMARY)
        nodes, level = -(-nodes // fan_in), level + 1
        if level % 4 == 0 and nodes > 1:
            out = stage(out, f"coreset_level{level}")
    return out


def chain_reduce(pts: DataFrame, k: int, ps: int, m: int | None = None, seed: int = 0) -> DataFrame:
    """Read a chunk, summarize, unite with what is held, reduce again: one task, every chunk pays for all later ones.

    A baseline that cannot be spread: more than ``SINGLE_ROWS`` points are refused. One
    chunk and one summary are held at a time.
    """
    ship_package(pts.sparkSession)
    m = m or FACTOR * k

    def run(batches):
        held = None
        for i, (x, w) in enumerate(_chunks(batches, ps)):
            one = SphereTree(m, x.shape[1], [seed, i])
            one.offer(x, w)
            new = one.rows()
            if held is not None:
                new = tuple(np.concatenate(v) for v in zip(held, new))
                if len(new[1]) > m:
                    again = SphereTree(m, x.shape[1], [seed, i, 1])
                    again.offer(*new)
                    new = again.rows()
            held = new
        if held is not None:
            yield _summary_batch(0, 0, *held)

    return _one_task(pts).mapInArrow(run, SUMMARY)


def _one_task(pts: DataFrame) -> DataFrame:
    rows = points(pts)
    if rows.count() > SINGLE_ROWS:
        raise ValueError("too many points for one task: use the tree")
    return rows.repartition(1).sortWithinPartitions("id")


def _chunks(batches, ps: int):
    """Points and weights of ``ps`` consecutive rows at a time."""
    xs, ws, have = [], [], 0
    for b in batches:
        x, w = (to_matrix(b.column(1)), b.column(2).to_numpy()) if b.num_rows else (None, ())
        at = 0
        while at < len(w):
            take = min(ps - have, len(w) - at)
            xs.append(x[at : at + take])
            ws.append(w[at : at + take])
            have, at = have + take, at + take
            if have == ps:
                yield np.concatenate(xs), np.concatenate(ws)
                xs, ws, have = [], [], 0
    if have:
        yield np.concatenate(xs), np.concatenate(ws)


def coupled_tree(pts: DataFrame, k: int, l: int, ps: int, seed: int = 0) -> DataFrame:  # noqa: E741
    """One decomposition for each summarizer run: projection and insertion as one unit in a binary tree."""
    return tree_full(pts, TreeParams(l=l, ps=ps, np=[1, 2], seed=seed)).select(*SUMMARY_COLUMNS)


def project_then_cluster(pts: DataFrame, k: int, l: int, ps: int, seed: int = 1) -> tuple[list, list[float]]:  # noqa: E741
    """Project chunk by chunk, keep all points (written to the shared folder), cluster in further passes."""
    kept = stage(linalg.project(points(pts).withColumn("piece", F.expr(f"id div {ps}")), l, seed=seed).select("id", "x", "w"), "projected")
    return clustering.kmeanspp(kept, k, seed)


def global_projection(pts: DataFrame, k: int, l: int, seed: int = 1) -> tuple[list, list[float]]:  # noqa: E741
    """The best-fit subspace of the whole table first, then clustering in it: two passes and more."""
    rows = points(pts)
    _, v = linalg.global_basis(rows, l)
    return clustering.kmeanspp(stage(linalg.project_global(rows, v), "projected"), k, seed)


def running_subspace(pts: DataFrame, k: int, l: int, ps: int, m: int | None = None, seed: int = 0) -> DataFrame:  # noqa: E741
    """Each piece in the best-fit subspace of all points so far, into one summarizer.

    Every piece needs the one before it, so this is one task: more than ``SINGLE_ROWS``
    points are refused. One piece, one Gram matrix and one summarizer are held.
    """
    ship_package(pts.sparkSession)
    m = m or FACTOR * k

    def run(batches):
        tree, gram = None, 0.0
        for p, c in _chunks(batches, ps):
            gram = gram + (p * c[:, None]).T @ p
            v = np.linalg.eigh(gram)[1][:, ::-1][:, :l].T
            tree = tree or SphereTree(m, p.shape[1], seed)
            tree.offer((p @ v.T) @ v, c)
        if tree is not None:
            yield _summary_batch(0, 0, *tree.rows())

    return _one_task(pts).mapInArrow(run, SUMMARY)


def uniform_sample(pts: DataFrame, size: int, seed: int = 1) -> DataFrame:
    """A keyed sample of ``size`` points, each with an equal whole share of the weight."""
    rows = points(pts)
    n = rows.count()
    picked = rows.orderBy(arithmetic_hash(F.col("id"), seed), "id").limit(size).withColumn("_r", F.row_number().over(clustering.Window.orderBy("id")))  # `size` rows
    share = F.lit(n // min(size, max(n, 1))) + F.when(F.col("_r") <= n % min(size, max(n, 1)), 1).otherwise(0)
    return picked.select(F.lit(0).alias("level"), F.lit(0).cast("bigint").alias("node"), "id", "x", share.cast("bigint").alias("w"), F.lit(0.0).alias("ss_within"))


def brute_force(x: np.ndarray, k: int = 2, w: np.ndarray | None = None) -> float:
    """Least cost over all partitions in at most ``k`` parts, for up to twelve points."""
    n = len(x)
    if n > 12:
        raise ValueError("brute force is for at most twelve points")
    w = np.ones(n) if w is None else w
    best = np.inf

    def cost(label: list[int]) -> float:
        total = 0.0
        for c in set(label):
            at = np.array([i for i, z in enumerate(label) if z == c])
            mean = np.average(x[at], axis=0, weights=w[at])
            total += float((w[at] * ((x[at] - mean) ** 2).sum(1)).sum())
        return total

    def grow(label: list[int], used: int) -> None:
        nonlocal best
        if len(label) == n:
            best = min(best, cost(label))
            return
        for c in range(min(used + 1, k)):
            grow([*label, c], max(used, c + 1))

    grow([], 0)
    return best
