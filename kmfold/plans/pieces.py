"""Forming pieces, and the shape of the computation tree over them."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kmfold.staging import stage


def by_key(pts: DataFrame, ps: int, key: str = "id") -> DataFrame:
    """Dense keys: ``ps`` consecutive ones form a piece."""
    return pts.withColumn("piece", F.expr(f"{key} div {int(ps)}"))


def by_hash(pts: DataFrame, pieces: int, key: str = "id") -> DataFrame:
    """Order-free pieces whose sizes are only near equal."""
    return pts.withColumn("piece", F.pmod(F.xxhash64(key), F.lit(pieces)))


def in_split(pts: DataFrame, ps: int) -> DataFrame:
    """``ps`` rows of a partition in the order they lie there form a piece; no row moves, the last piece is short.

    A piece is named by its partition (high half) and its place in it.
    """
    row = F.monotonically_increasing_id()  # partition in the bits above 33, row below
    named = pts.withColumn("_row", row)
    part, at = F.shiftright("_row", 33), F.col("_row").bitwiseAND(F.lit((1 << 33) - 1))
    return named.withColumn("piece", F.shiftleft(part, 33) + F.floor(at / F.lit(int(ps))).cast("bigint")).drop("_row")


def by_time(pts: DataFrame, ts: str, width: str) -> DataFrame:
    """Pieces of a time width: neighbours in time tend to share a subspace."""
    start = F.window(F.col(ts).cast("timestamp"), width)["start"]
    return pts.withColumn("piece", F.unix_seconds(start))


def dense_index(df: DataFrame, order: list[str | Column], out: str = "id") -> DataFrame:
    """Dense ids in the given order without a one-task window.

    Rows are range-partitioned and numbered inside their partition; the partitions'
    sizes (one row each) give the first number of each. The range-partitioned rows are
    written once, since the partition ids of a second run could differ.
    """
    n = max(1, df.rdd.getNumPartitions() if df.isStreaming else int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    ranged = df.repartitionByRange(n, *order).sortWithinPartitions(*order)
    numbered = stage(ranged.withColumn("_part", F.spark_partition_id()).withColumn("_mono", F.monotonically_increasing_id()), "dense_index")
    sizes = numbered.groupBy("_part").agg(F.count("*").alias("_n"), F.min("_mono").alias("_first"))
    running = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # one row a partition
    base = sizes.select("_part", "_first", F.coalesce(F.sum("_n").over(running), F.lit(0)).alias("_base"))
    return numbered.join(F.broadcast(base), "_part").withColumn(out, F.col("_base") + F.col("_mono") - F.col("_first")).drop("_part", "_mono", "_first", "_base")


@dataclass
class TreeParams:
    """Target dimension, piece size, pieces a node (by level, the last repeats), summary size of a node."""

    l: int  # noqa: E741
    ps: int
    np: int | list[int] = 3
    m: int | None = None
    project_levels: str = "all"
    svd: str = "random"
    flush: str = "promote"
    seed: int = 0
    np_by_level: list[int] = field(init=False)

    def __post_init__(self):
        self.np_by_level = [self.np] if isinstance(self.np, int) else list(self.np)
        if min(self.np_by_level) < 1 or self.ps < 1 or self.l < 1:
            raise ValueError("np, ps and l must be positive")
        if self.project_levels not in ("all", "leaf", "none") or self.flush not in ("promote", "merge"):
            raise ValueError("project_levels: all, leaf, none; flush: promote, merge")
        self.m = self.m or self.ps

    def fan(self, level: int) -> int:
        return self.np_by_level[min(level, len(self.np_by_level) - 1)]

    def projects(self, level: int) -> bool:
        return self.project_levels == "all" or self.project_levels == "leaf" and level == 0


def plan_levels(n_points: int, params: TreeParams) -> list[dict]:
    """Nodes, decompositions and summarizer runs of each level; the last has one node.

    ``promote`` keeps half-filled nodes and carries them up; ``merge`` gives the last
    half-filled node's pieces to its left neighbour.
    """
    pieces, level, out = -(-n_points // params.ps), 0, []
    while True:
        fan = params.fan(level)
        if level > 0 and fan < 2:
            fan = 2
        nodes = max(1, pieces // fan if params.flush == "merge" else -(-pieces // fan))
        out.append({"level": level, "pieces": pieces, "fan": fan, "nodes": nodes, "svds": pieces if params.projects(level) else 0})
        if nodes == 1:
            return out
        pieces, level = nodes, level + 1


def parent(node: Column, fan: int, nodes: int, flush: str) -> Column:
    """Node that takes in child ``node`` (a piece on level 0)."""
    up = F.floor(node / F.lit(fan)).cast("bigint")
    return F.least(up, F.lit(nodes - 1).cast("bigint")) if flush == "merge" else up


def tree_counts(n_points: int, params: TreeParams) -> dict:
    """Decompositions, summarizer runs, depth, and reductions that a point takes part in."""
    levels = plan_levels(n_points, params)
    return {"levels": len(levels), "svds": sum(x["svds"] for x in levels), "runs": sum(x["nodes"] for x in levels), "reductions_per_point": len(levels)}


def chain_counts(n_points: int, ps: int) -> dict:
    """The chain strategy: the first piece takes part in every later reduction."""
    pieces = -(-n_points // ps)
    return {"reductions": max(0, pieces - 1), "reductions_first_piece": max(0, pieces - 1)}
