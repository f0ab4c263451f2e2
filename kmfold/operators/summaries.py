"""Weighted summaries of tables: direct, piecewise, tree, and merge-and-reduce.

Every kernel runs inside an Arrow node and holds one piece, one decomposition and
one summarizer at a time. Generators are keyed by seed, level and node and rows are
ordered by id inside a node, so a retried task gives the same rows. Levels after the
first see summaries only: rows fall by the number of pieces a node takes in.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kmfold.functions.arrays import to_column, to_matrix
from kmfold.operators.linalg import project_matrix
from kmfold.operators.sphere import SphereTree
from kmfold.plans.pieces import TreeParams, dense_index, parent, plan_levels
from kmfold.staging import ship_package, stage

FACTOR = 200
SUMMARY = "level int, node bigint, id bigint, x array<double>, w bigint, ss_within double"
COUNTERS = "n_in bigint, w_in bigint, n_out bigint, rebuilds bigint, dist_evals bigint, splits bigint, svds bigint, threshold double, e_proj double, e_merge double, svd_cpu_s double, insert_cpu_s double"
#: A node's rows carry its counters; readers take them from the row of id 0.
FULL = f"{SUMMARY}, {COUNTERS}"
SINGLE_ROWS = 20_000_000
CHECKPOINT_LEVELS = 4
SUMMARY_COLUMNS = ["level", "node", "id", "x", "w", "ss_within"]


def points(pts: DataFrame, weight_col: str | None = None) -> DataFrame:
    """The columns a kernel needs: id, x and a whole weight (1 where there is none)."""
    w = F.col(weight_col) if weight_col else F.col("w") if "w" in pts.columns else F.lit(1)
    return pts.select(F.col("id").cast("bigint").alias("id"), F.col("x").cast("array<double>").alias("x"), w.cast("bigint").alias("w"))


class Node:
    """One summarizer with its counters."""

    def __init__(self, m: int, level: int, node: int, seed: int, **options):
        self.m, self.level, self.node, self.seed, self.options = m, level, node, seed, options
        self.tree: SphereTree | None = None
        self.svds, self.e_proj, self.svd_s, self.insert_s = 0, 0.0, 0.0, 0.0

    def take(self, x: np.ndarray, w: np.ndarray, l: int, kind: str, key: int, within: np.ndarray | None = None) -> None:  # noqa: E741
        """Project one piece and feed it with the inner costs that its points bring along."""
        if not len(x):
            return
        t = time.process_time()
        y, moved = project_matrix(x, l, w, kind, [self.seed, self.level, self.node, key])
        self.svds += kind != "none"  # asked for, even where l reaches the rank and nothing is computed
        u = time.process_time()
        if self.tree is None:
            self.tree = SphereTree(self.m, x.shape[1], [self.seed, self.level, self.node], **self.options)
        self.tree.offer(y, w, within)
        self.svd_s += u - t
        self.insert_s += time.process_time() - u
        self.e_proj += moved

    def batch(self, inherited: float = 0.0) -> pa.RecordBatch | None:
        if self.tree is None:
            return None
        mean, w, within = self.tree.rows()
        n, c = len(w), self.tree.counters
        one = {"n_in": c["n_in"], "w_in": c["w_in"], "n_out": n, "rebuilds": c["rebuilds"], "dist_evals": c["dist_evals"], "splits": c["splits"], "svds": self.svds}
        reals = {"threshold": self.tree.limit, "e_proj": self.e_proj, "e_merge": self.tree.merged(), "svd_cpu_s": self.svd_s, "insert_cpu_s": self.insert_s}
        cols = {"level": pa.array(np.full(n, self.level), pa.int32()), "node": pa.array(np.full(n, self.node), pa.int64()), "id": pa.array(np.arange(n), pa.int64()), "x": to_column(mean), "w": pa.array(w, pa.int64()), "ss_within": pa.array(within)}
        cols |= {k: pa.array(np.full(n, v), pa.int64()) for k, v in one.items()} | {k: pa.array(np.full(n, v, float)) for k, v in reals.items()}
        return pa.RecordBatch.from_pydict(cols)


def _fed(batches, ps: int, node_of, make, l, kind, ids: bool):  # noqa: E741
    """Feed pieces of ``ps`` consecutive rows of a stream of batches to nodes that ``node_of`` names."""
    xs, ws, have, piece, node = [], [], 0, 0, None
    for b in batches:
        if not b.num_rows:
            continue
        x, w = to_matrix(b.column(1)), b.column(2).to_numpy()
        at = 0
        while at < len(x):
            take = min(ps - have, len(x) - at)
            xs.append(x[at : at + take])
            ws.append(w[at : at + take])
            have += take
            at += take
            if have == ps:
                name = node_of(piece)
                if node is not None and node.node != name:
                    yield node.batch()
                    node = None
                node = node or make(name)
                node.take(np.concatenate(xs), np.concatenate(ws), l, kind, piece)
                xs, ws, have, piece = [], [], 0, piece + 1
    if have:
        name = node_of(piece)
        if node is not None and node.node != name:
            yield node.batch()
            node = None
        node = node or make(name)
        node.take(np.concatenate(xs), np.concatenate(ws), l, kind, piece)
    if node is not None:
        yield node.batch()


def piecewise_full(pts: DataFrame, k: int, ps: int, l: int | None = None, m: int | None = None, svd: str = "random", mode: str = "sharded", seed: int = 0, factor: int = FACTOR, reduce_to_one: bool = True, **options) -> DataFrame:  # noqa: E741
    """Pieces of ``ps`` points, each projected on ``l`` dimensions, fed to one summarizer.

    ``single`` keeps the order of ids and runs in one task: small inputs only.
    ``sharded`` runs one summarizer a partition, in the order of ids inside it, without
    moving a point, then reduces the union of the summaries. ``svd='none'`` is the
    direct method.
    """
    spark = pts.sparkSession
    ship_package(spark)
    m = m or factor * k
    rows = points(pts)
    if mode == "single":
        if rows.count() > SINGLE_ROWS:
            raise ValueError("too many points for one summarizer: use mode='sharded' or the tree")
        rows = rows.repartition(1)
    elif mode != "sharded":
        raise ValueError("mode must be single or sharded")
    rows = rows.sortWithinPartitions("id")

    def run(batches):
        from pyspark import TaskContext

        shard = TaskContext.get().partitionId()
        yield from (b for b in _fed(batches, ps, lambda piece: shard, lambda name: Node(m, 0, name, seed, **options), l or 1 << 30, svd if l else "none", True) if b is not None)

    out = rows.mapInArrow(run, FULL)
    if mode == "single" or not reduce_to_one:
        return out
    return reduce_levels(stage(out, "shard_summaries"), m, seed=seed, **options)


def direct_summary(pts: DataFrame, k: int, m: int | None = None, mode: str = "sharded", seed: int = 0, factor: int = FACTOR, weight_col: str | None = None, **options) -> DataFrame:
    """One-pass weighted summary by spheres, without projection."""
    rows = points(pts, weight_col)
    return piecewise_full(rows, k, 4096, None, m, "none", mode, seed, factor, **options).select(*SUMMARY_COLUMNS)


def piecewise_summary(pts: DataFrame, k: int, ps: int, l: int, m: int | None = None, svd: str = "random", mode: str = "sharded", seed: int = 0, factor: int = FACTOR, **options) -> DataFrame:  # noqa: E741
    return piecewise_full(pts, k, ps, l, m, svd, mode, seed, factor, **options).select(*SUMMARY_COLUMNS)


def union_summaries(*frames: DataFrame) -> DataFrame:
    """Summaries of parts together summarize the whole; the error does not grow."""
    out = frames[0].select(*SUMMARY_COLUMNS)
    for f in frames[1:]:
        out = out.unionByName(f.select(*SUMMARY_COLUMNS))
    return out


def _reduce(df: DataFrame, m: int, level: int, l: int | None, kind: str, seed: int, options: dict) -> DataFrame:  # noqa: E741
    """One summarizer for each ``up`` group of child summaries, children in the order of their nodes."""

    def run(key, batches):
        t = pa.Table.from_batches(list(batches)).sort_by([("node", "ascending"), ("id", "ascending")])
        node = Node(m, level, int(key[0].as_py()), seed, **options)
        x, w, child, within = to_matrix(t.column("x")), t.column("w").to_numpy(), t.column("node").to_numpy(), t.column("ss_within").to_numpy()
        for c in np.unique(child):
            mine = child == c
            node.take(x[mine], w[mine], l or 1 << 30, kind if l else "none", int(c), within[mine])
        yield node.batch()

    # the inner costs of the children move up with their rows
    columns = df.select("up", "node", "id", "x", "w", "ss_within")
    return columns.groupBy("up").applyInArrow(run_iter(run), FULL)


def run_iter(f):
    """Mark a grouped function as one over an iterator of batches."""
    from collections.abc import Iterator

    def g(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from f(key, batches)

    g.__annotations__ = {"key": tuple[pa.Scalar, ...], "batches": Iterator[pa.RecordBatch], "return": Iterator[pa.RecordBatch]}
    return g


def reduce_summary(df: DataFrame, k: int, m: int | None = None, seed: int = 0, factor: int = FACTOR, **options) -> DataFrame:
    """Reduce a union of bounded summaries to one of at most ``m`` rows (weighted insertion)."""
    ship_package(df.sparkSession)
    rows = df.select(F.lit(0).cast("bigint").alias("up"), F.col("node").cast("bigint").alias("node"), "id", "x", "w", "ss_within")
    return _reduce(rows, m or factor * k, 1, None, "none", seed, options).select(*SUMMARY_COLUMNS)


def reduce_levels(df: DataFrame, m: int, fan: int = 4, seed: int = 0, l: int | None = None, kind: str = "none", **options) -> DataFrame:  # noqa: E741
    """Reduce node summaries (read twice: stage them) by a tree of degree ``fan`` until one node is left.

    Nodes are numbers, best without gaps (a gap costs nothing but levels): their least
    and greatest alone reach the driver.
    """
    ship_package(df.sparkSession)
    ends = df.agg(F.min("node").alias("low"), F.max("node").alias("high")).first()
    if ends["low"] is None or ends["low"] == ends["high"]:
        return df
    rows = df.withColumn("node", F.col("node") - F.lit(ends["low"]))
    nodes, level = ends["high"] - ends["low"] + 1, 1
    while nodes > 1:
        rows = rows.withColumn("up", F.expr(f"node div {fan}"))
        rows = _reduce(rows, m, level, l, kind, seed, options)
        nodes, level = -(-nodes // fan), level + 1
        if level % CHECKPOINT_LEVELS == 0 and nodes > 1:
            rows = stage(rows, f"level{level}")
    return rows


def merge_reduce(pts: DataFrame, k: int, ps: int, m: int | None = None, fan_in: int = 2, seed: int = 0, n_points: int | None = None, **options) -> DataFrame:
    """Merge-and-reduce: the tree of degree ``fan_in`` over summaries of single pieces, without projection."""
    params = TreeParams(l=1, ps=ps, np=[1, fan_in], m=m or ps, project_levels="none", svd="none", seed=seed)
    return tree_full(pts, params, n_points, **options).select(*SUMMARY_COLUMNS)


def tree_full(pts: DataFrame, params: TreeParams, n_points: int | None = None, keep_levels: bool = False, **options) -> DataFrame:
    """The wide computation tree; rows with counters, of the root or of all levels.

    Ids without gaps name the pieces: piece = (id - least id) div ps, node = piece div
    np. Others are replaced by their places in the order of ids, for one more exchange.
    Level 0 is one exchange by node (none where the table already lies so); each further
    level exchanges the summaries below it, and the last level is one node. The driver
    only composes the plan. ``n_points``, where given, must be the number of rows.
    """
    spark = pts.sparkSession
    ship_package(spark)
    rows = points(pts)
    told = rows.agg(F.count("*").alias("n"), F.count("id").alias("named"), F.min("id").alias("low"), F.max("id").alias("high")).first()  # a scan of the ids alone
    n = told["n"]
    if n_points is not None and n_points != n:
        raise ValueError(f"n_points is {n_points}, the table has {n} rows")
    if not n:
        return spark.createDataFrame([], FULL)
    if told["named"] < n or told["high"] - told["low"] + 1 != n:
        rows = dense_index(rows.drop("_place"), ["id"], "_place").drop("id").withColumnRenamed("_place", "id").select("id", "x", "w")
    elif told["low"]:
        rows = rows.withColumn("id", F.col("id") - F.lit(told["low"]))
    levels = plan_levels(n, params)
    ps, kind = params.ps, params.svd

    def leaf(key, batches):
        t = pa.Table.from_batches(list(batches)).sort_by("id")
        node = Node(params.m, 0, int(key[0].as_py()), params.seed, **options)
        ids, x, w = t.column("id").to_numpy(), to_matrix(t.column("x")), t.column("w").to_numpy()
        piece = ids // ps
        for p in np.unique(piece):
            mine = piece == p
            node.take(x[mine], w[mine], params.l, kind if params.projects(0) else "none", int(p))
        yield node.batch()

    first = levels[0]
    fed = rows.withColumn("up", parent(F.expr(f"id div {ps}"), first["fan"], first["nodes"], params.flush))
    out = fed.select("up", "id", "x", "w").groupBy("up").applyInArrow(run_iter(leaf), FULL)
    kept = [out]
    for lv in levels[1:]:
        if keep_levels or lv["level"] % CHECKPOINT_LEVELS == 0:
            out = kept[-1] = stage(out, f"tree_level{lv['level'] - 1}")
        up = out.withColumn("up", parent(F.col("node"), lv["fan"], lv["nodes"], params.flush))
        out = _reduce(up, params.m, lv["level"], params.l if params.projects(lv["level"]) else None, kind, params.seed, options)
        kept.append(out)
    if not keep_levels:
        return out
    result = kept[0]
    for f in kept[1:]:
        result = result.unionByName(f)
    return result


def tree_summary(pts: DataFrame, k: int, l: int, ps: int | None = None, np: int | list[int] = 3, seed: int = 0, factor: int = FACTOR, n_points: int | None = None, svd: str = "random", project_levels: str = "all", flush: str = "promote", **options) -> DataFrame:  # noqa: E741
    """Project and summarize on every level of the tree; piece size and node size are ``factor * k`` by default."""
    params = TreeParams(l=l, ps=ps or factor * k, np=np, svd=svd, seed=seed, project_levels=project_levels, flush=flush)
    return tree_full(pts, params, n_points, **options).select(*SUMMARY_COLUMNS)


def node_counters(full: DataFrame) -> DataFrame:
    """One row a node: what went in and out, rebuilds, distances, splits, threshold, errors and CPU seconds."""
    names = [c.split(" ")[0] for c in COUNTERS.split(", ")]
    return full.filter("id = 0").select("level", "node", *names)


def total_error(full: DataFrame) -> float:
    """Bound on the moved distance: the root of squared movements, added over the levels.

    For every set of centers the roots of the costs on input and summary differ by at
    most this much. Needs the rows of all levels.
    """
    per = node_counters(full).groupBy("level").agg(F.sum("e_proj").alias("p"), F.sum("e_merge").alias("m")).collect()
    return float(sum((r["p"] or 0.0) ** 0.5 + (r["m"] or 0.0) ** 0.5 for r in per))


def choose(n: int, d: int, k: int) -> str:
    """Advice on the method: few dimensions direct; many dimensions piecewise, or the tree for a long stream."""
    if d <= 100 or k >= d:
        return "direct"
    return "piecewise" if n <= 1_000_000 else "tree"
