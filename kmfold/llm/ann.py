"""Nearest neighbours by a permutation index.

A bounded sample of vectors serves as pivots. A vector is represented by the order of
its nearest pivots and posted in the inverted lists of its nearest list pivots. A query
visits the lists of its own nearest list pivots only; a pair that shares several lists
meets in the one that the query visits first. Inside a list the postings of the query's
pivots rank the vectors by footrule distance, and the best share is reranked exactly.
Long lists are split, and so are the queries of a list; neither side is broadcast, and
every row is indexed.

For the inner product, indexed vectors carry one more coordinate that gives all the
same length, so that the nearest direction is the largest product.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kmfold.staging import ship_package, stage

PIVOTS = 512
ORDER = 64
#: Lists, lists that a vector is posted in, and lists that a query visits: recall above 0.94 on even random directions.
LISTS, POSTED, VISITED = 128, 4, 32
LIST_ROWS, QUERY_ROWS = 8192, 4096
CANDIDATE_SHARE = 0.3
LEAST_CANDIDATES = 200


def pivot_orders(vectors: np.ndarray, pivots: np.ndarray, order: int) -> np.ndarray:
    """The ``order`` nearest pivots of each vector, nearest first, ties to the smaller pivot."""
    likeness = vectors @ pivots.T
    k = min(order, pivots.shape[0])
    part = np.argpartition(-likeness, k - 1, axis=1)[:, :k]
    part.sort(axis=1)
    rank = np.argsort(-np.take_along_axis(likeness, part, axis=1), axis=1, kind="stable")
    return np.take_along_axis(part, rank, axis=1).astype(np.int16)


class InvertedFiles:
    """For every pivot, the vectors of a block that hold it in their order, with its rank there."""

    def __init__(self, orders: np.ndarray, pivots: int):
        n, k = orders.shape
        flat = orders.ravel().astype(np.int64)
        by_pivot = np.argsort(flat, kind="stable")
        self.vector, self.rank = (by_pivot // k).astype(np.int32), (by_pivot % k).astype(np.int32)
        self.start = np.searchsorted(flat[by_pivot], np.arange(pivots + 1))
        self.size, self.order = n, k

    def footrule(self, query_order: np.ndarray) -> np.ndarray:
        """Distance of the query's order to that of each vector; an absent pivot counts as rank ``order``."""
        k = self.order
        saved = np.zeros(self.size)
        for i, p in enumerate(query_order.tolist()):
            a, b = self.start[p], self.start[p + 1]
            # against absence on both sides, (k - i) + (k - j), a shared pivot costs |i - j|
            saved += np.bincount(self.vector[a:b], (k - i) + (k - self.rank[a:b]) - np.abs(i - self.rank[a:b]), self.size)
        return k * (k + 1) - saved


def search_list(index: tuple, asked: tuple, this: int, pivots: int, nearest: int, share: float, least: int):
    """The best ``nearest`` rows of a part of list ``this`` for each of its queries.

    ``index``: ids, vectors, orders and posted lists; ``asked``: row keys, ids, vectors,
    orders and visited lists (in the order of the visit).
    """
    ids, vectors, orders, posted = index
    keys, query_ids, queries, query_orders, visited = asked
    files = InvertedFiles(orders, pivots)
    m = max(least, int(np.ceil(share * len(ids))))
    out_k, out_q, out_v, out_s = [], [], [], []
    lists = int(max(posted.max(), visited.max())) + 1
    for key, qid, q, qo, seen in zip(keys.tolist(), query_ids.tolist(), queries, query_orders, visited):
        before = np.zeros(lists, bool)
        before[seen[: int(np.argmax(seen == this))]] = True
        near = np.flatnonzero(~before[posted].any(axis=1) & (ids != qid))
        if len(near) > m:
            far = files.footrule(qo)[near]
            near = near[np.argpartition(far, m - 1)[:m]]
        score = np.einsum("ij,j->i", vectors[near], q)
        if len(near) > nearest:
            cut = np.partition(score, len(score) - nearest)[len(score) - nearest]
            keep = score >= cut
            near, score = near[keep], score[keep]
        best = np.lexsort((ids[near], -score))[:nearest]
        out_k.append(np.full(len(best), key))
        out_q.append(np.full(len(best), qid))
        out_v.append(ids[near[best]])
        out_s.append(score[best])
    return tuple(map(np.concatenate, (out_k, out_q, out_v, out_s)))


def usable(embeddings: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """Rows whose vector takes part: not null, not zero, all components present and finite."""
    x = F.col("_x")
    fine = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) != float("inf")))
    rows = embeddings.select(F.col(id_col).cast("long").alias("_id"), F.col(vector_col).cast("array<double>").alias("_x"))
    return rows.filter(F.col("_id").isNotNull() & x.isNotNull() & (F.size(x) > 0) & fine & F.exists(x, lambda v: v != 0))


def search(embeddings: DataFrame, nearest: int = 20, every: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", pivots: int = PIVOTS, order: int = ORDER, lists: int = LISTS, posted: int = POSTED, visited: int = VISITED, share: float = CANDIDATE_SHARE, least: int = LEAST_CANDIDATES) -> DataFrame:
    """Nearest rows of every row whose id is divisible by ``every``, by inner product.

    Vectors that are null, zero, or hold a null or non-finite component take no part,
    neither do rows without an id or with another length than most vectors have (of
    equally frequent lengths the largest counts). A row is never its own neighbour;
    rows of a repeated id are not each other's, and each of them is a query with ranks
    of its own. Fewer candidates than ``nearest`` give fewer rows; an empty table gives
    an empty result.
    """
    spark = embeddings.sparkSession
    ship_package(spark)
    rows = usable(embeddings, id_col, vector_col)
    result = "query_id long, rank int, vec_id long, score double"
    square = F.aggregate("_x", F.lit(0.0), lambda s, v: s + v * v)
    common = rows.groupBy(F.size("_x").alias("width")).agg(F.count("*").alias("n"), F.max(square).alias("square")).orderBy(F.desc("n"), F.desc("width")).first()
    if common is None:
        return spark.createDataFrame([], result)
    width, longest = common["width"], float(common["square"])
    rows = rows.filter(F.size("_x") == width)
    sample = rows.orderBy(F.xxhash64("_id"), "_id").limit(pivots).collect()  # `pivots` rows, whatever the input

    def lifted(x):
        return np.column_stack([x, np.sqrt(np.maximum(longest - (x * x).sum(axis=1), 0.0))])

    chosen = lifted(np.array([r["_x"] for r in sample]))
    held = spark.sparkContext.broadcast(chosen / np.linalg.norm(chosen, axis=1, keepdims=True))
    n_pivots, n_lists = len(chosen), min(lists, len(chosen))
    posted, visited = min(posted, n_lists), min(visited, n_lists)

    def permute(batches):
        from pyspark import TaskContext

        row = TaskContext.get().partitionId() << 40
        for b in batches:
            ids = b.column(0).to_numpy()
            x = np.asarray(b.column(1).flatten()).reshape(len(ids), width)
            directions, asks = lifted(x), ids % every == 0
            flat = np.column_stack([x, np.zeros(len(ids))])
            keys = row + np.arange(len(ids))
            row += len(ids)
            rows = [keys, ids, x, pivot_orders(directions, held.value, order), pivot_orders(directions, held.value[:n_lists], posted)]
            yield narrow(asks, *rows, pivot_orders(flat, held.value, order), pivot_orders(flat, held.value[:n_lists], visited))

    def narrow(asks, keys, ids, x, orders, near, query_orders, visits):
        def cells(v, there=None):
            return pa.array([r.tobytes() if there is None or there[i] else None for i, r in enumerate(np.ascontiguousarray(v))], pa.binary())

        def shorts(v, there=None):
            return pa.array([r.tolist() if there is None or there[i] else None for i, r in enumerate(v)], pa.list_(pa.int16()))

        return pa.RecordBatch.from_arrays([pa.array(keys), pa.array(ids), cells(x), cells(orders), shorts(near), cells(query_orders, asks), shorts(visits, asks)], ["key", "id", "x", "orders", "posted", "query_orders", "visited"])

    # one narrow row a vector; what follows is packed by list, batch by batch
    told = stage(rows.mapInArrow(permute, "key long, id long, x binary, orders binary, posted array<short>, query_orders binary, visited array<short>"), "permutations")
    sides = {"index": told.select("key", "id", "x", "orders", F.col("posted").alias("lists")), "query": told.filter("visited is not null").select("key", "id", "x", F.col("query_orders").alias("orders"), F.col("visited").alias("lists"))}
    # at most two numbers a list: how many parts its vectors and its queries make
    sizes = {(kind, r["list"]): r["count"] for kind, side in sides.items() for r in side.select(F.explode("lists").alias("list")).groupBy("list").count().collect()}
    parts = {kind: F.element_at(F.array(*[F.lit(max(1, -(-sizes.get((kind, i), 0) // most))) for i in range(n_lists)]), F.col("list") + 1) for kind, most in (("index", LIST_ROWS), ("query", QUERY_ROWS))}

    def pack(batches):
        for b in batches:
            if not b.num_rows:
                continue
            columns = [np.frombuffer(b"".join(b.column(i).to_pylist()), np.uint8).reshape(b.num_rows, -1) for i in (2, 3)]
            near = np.asarray(b.column(4).flatten(), np.int16).reshape(b.num_rows, -1)
            by_list = np.argsort(near.ravel(), kind="stable")
            owner, name = by_list // near.shape[1], near.ravel()[by_list]
            cuts = np.flatnonzero(np.append(True, name[1:] != name[:-1]))
            held_rows = [owner[a:z] for a, z in zip(cuts, np.append(cuts[1:], len(owner)))]
            arrays = {"keys": b.column(0).to_numpy(), "ids": b.column(1).to_numpy(), "x": columns[0], "orders": columns[1], "lists": near}
            yield pa.RecordBatch.from_pydict({"list": pa.array(name[cuts], pa.int32())} | {c: pa.array([v[p].tobytes() for p in held_rows], pa.binary()) for c, v in arrays.items()})

    def dealt(kind, own, other, other_kind):
        cells = sides[kind].mapInArrow(pack, "list int, keys binary, ids binary, x binary, orders binary, lists binary")
        mine = F.pmod(F.xxhash64("keys", "ids"), parts[kind]).cast("int")
        return cells.withColumn(own, mine).withColumn(other, F.explode(F.sequence(F.lit(0), parts[other_kind] - 1)))

    index, asked = dealt("index", "_i", "_q", "query"), dealt("query", "_q", "_i", "index")

    def unpack(table):
        def joined(name, kind):
            return np.concatenate([np.frombuffer(v.as_py(), kind) for v in table.column(name)])

        keys, ids = joined("keys", np.int64), joined("ids", np.int64)
        return keys, ids, joined("x", np.float64).reshape(len(ids), width), joined("orders", np.int16).reshape(len(ids), -1), joined("lists", np.int16).reshape(len(ids), -1)

    def meet(left, right):
        found = tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.float64))
        if left.num_rows and right.num_rows:
            found = search_list(unpack(left)[1:], unpack(right), left.column("list")[0].as_py(), n_pivots, nearest, share, least)
        return pa.table({n: pa.array(v, t) for n, v, t in zip(("key", "query_id", "vec_id", "score"), found, (pa.int64(), pa.int64(), pa.int64(), pa.float64()))})

    columns, task = ["list", "_i", "_q", "keys", "ids", "x", "orders", "lists"], ["list", "_i", "_q"]
    found = index.select(columns).groupBy(*task).cogroup(asked.select(columns).groupBy(*task)).applyInArrow(meet, "key long, query_id long, vec_id long, score double")
    best = Window.partitionBy("key").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= nearest).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
