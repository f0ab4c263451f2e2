"""Lloyd's iteration, seeding and k-means++ on tables and on summaries."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kmfold.functions.cost import assign, check_centers
from kmfold.functions.hashing import uniform
from kmfold.functions.arrays import block_distances, to_column, to_matrix
from kmfold.staging import ship_package

CENTERS = "cid int, c array<double>"
SUMMARY_ROWS = 2_000_000


def centers_frame(spark: SparkSession, centers) -> DataFrame:
    rows = [(int(cid), [float(v) for v in c]) for cid, c in centers]
    return spark.createDataFrame(rows, CENTERS)


def weighted(pts: DataFrame) -> DataFrame:
    return pts if "w" in pts.columns else pts.withColumn("w", F.lit(1).cast("bigint"))


def lloyd_step(pts: DataFrame, centers: list, vectorized: bool | None = None) -> tuple[list, float]:
    """One assignment and one move of the centers: one scan, points stay where they are.

    Every task sums weights, vectors and costs by center before anything is exchanged. A
    center without points stays where it was. The bound on centers is that of ``assign``.
    """
    check_centers(centers)
    if not centers:
        raise ValueError("no centers")
    ship_package(pts.sparkSession)
    cids, c = [cid for cid, _ in centers], np.array([v for _, v in centers], float)

    def run(batches):
        w, ls, cost = np.zeros(len(c)), np.zeros_like(c), np.zeros(len(c))
        for b in batches:
            if not b.num_rows:
                continue
            x, weight = to_matrix(b.column(0)), b.column(1).to_numpy().astype(float)
            near = block_distances(x, c).argmin(axis=1)
            diff = x - c[near]
            cost += np.bincount(near, weight * np.einsum("ij,ij->i", diff, diff), len(c))
            w += np.bincount(near, weight, len(c))
            # rows by center, so that each center's sum is one slice
            order = np.argsort(near, kind="stable")
            first = np.flatnonzero(np.append(True, np.diff(near[order]) != 0))
            ls[near[order[first]]] += np.add.reduceat((x * weight[:, None])[order], first, axis=0)
        full = np.flatnonzero(w)
        yield pa.RecordBatch.from_pydict({"at": pa.array(full, pa.int32()), "w": pa.array(w[full]), "cost": pa.array(cost[full]), "ls": to_column(ls[full])})

    part = weighted(pts).select(F.col("x").cast("array<double>").alias("x"), "w").mapInArrow(run, "at int, w double, cost double, ls array<double>")
    flat = part.select("at", "w", "cost", F.posexplode("ls").alias("j", "v")).groupBy("at", "j").agg(F.sum("v").alias("v"), F.sum("w").alias("w"), F.sum("cost").alias("cost"))
    moved, total = c.copy(), 0.0
    for r in flat.collect():  # a number for each coordinate of the centers
        moved[r["at"], r["j"]] = r["v"] / r["w"]
        total += r["cost"] if r["j"] == 0 else 0.0
    return list(zip(cids, moved.tolist())), total


def lloyd(pts: DataFrame, init: list, max_iter: int = 20, tol: float = 1e-4) -> tuple[list, list[float]]:
    """Centers and the cost before each move; stops on no change, on a small decrease or after ``max_iter``.

    Only k centers travel between the steps, so no lineage grows.
    """
    centers, history = list(init), []
    for _ in range(max_iter):
        moved, cost = lloyd_step(pts, centers)
        history.append(cost)
        if moved == centers or len(history) > 1 and history[-2] - cost <= tol * history[-2]:
            break
        centers = moved
    return centers, history


def uniform_seeds(pts: DataFrame, k: int, seed: int = 1) -> list:
    """``k`` points in the order of a keyed hash: the same for every partitioning."""
    rows = pts.select("id", F.col("x").cast("array<double>").alias("x")).orderBy(uniform(F.col("id"), seed), "id").limit(k).collect()
    return [(i, list(r["x"])) for i, r in enumerate(rows)]


def d2_seeds(pts: DataFrame, k: int, seed: int = 1) -> list:
    """Squared-distance seeding on a full table: one aggregate a center.

    The next center is the first of an exponential race whose rates are the weighted
    squared distances, so each point wins with probability in proportion to its cost.
    """
    pts = weighted(pts)
    chosen = uniform_seeds(pts, 1, seed)
    while chosen and len(chosen) < k:
        near = assign(pts, chosen)
        u = (uniform(F.col("id"), seed + len(chosen)) * (2147483647.0 - 1) + 1) / 2147483648.0
        race = -F.log(u) / (F.col("w") * F.col("d2"))
        best = near.filter("d2 > 0").agg(F.min_by(F.struct("id", "x"), F.struct(race.alias("r"), F.col("id").alias("i"))).alias("p")).first()["p"]
        if best is None:
            break
        chosen.append((len(chosen), [float(v) for v in best["x"]]))
    return chosen


def race_seeds(pts: DataFrame, k: int, seed: int = 1, candidates: int = 1024) -> list:
    """Squared-distance seeding in a few scans instead of one for each center.

    Every point has one exponential clock that runs at the rate of its weighted squared
    distance to the centers so far; the next center is the point whose clock ends
    first, which is a draw in proportion to the distances. Rates only fall, so a clock
    ends no earlier than it would at today's rates: the points that could end before a
    time T, some hundreds by choice of T, are fetched once, and the race goes on among
    them until T. Then the next scan fetches more.
    """
    pts = weighted(pts)
    first = uniform_seeds(pts, 1, seed)
    if not first or k < 2:
        return first
    ship_package(pts.sparkSession)
    clock = -F.log((uniform(F.col("id"), seed + 1) * (2147483647.0 - 1) + 1) / 2147483648.0)
    rows = pts.select(F.col("id").cast("bigint").alias("id"), F.col("x").cast("array<double>").alias("x"), F.col("w").cast("double").alias("w"), clock.alias("clock"))
    chosen, times = [first[0][1]], [0.0]
    while len(chosen) < k:
        c, t = np.array(chosen), np.array(times)

        def run(batches, c=c, t=t):
            for b in batches:
                if b.num_rows:
                    end, cost = clock_ends(to_matrix(b.column(1)), b.column(2).to_numpy(), b.column(3).to_numpy(), c, t)
                    yield pa.RecordBatch.from_arrays([*b.columns[:4], pa.array(end), pa.array(cost)], ["id", "x", "w", "clock", "ends", "cost"])

        told = rows.mapInArrow(run, "id bigint, x array<double>, w double, clock double, ends double, cost double")
        total = told.agg(F.sum("cost")).first()[0] or 0.0
        if total <= 0:
            break  # no more distinct points
        until = times[-1] + candidates / 2 / total
        found = told.filter(F.col("ends") <= until).select("id", "x", "w", "clock").limit(64 * candidates).collect()
        found.sort(key=lambda r: r["id"])
        if len(found) == 64 * candidates:
            raise RuntimeError("the clocks are not even: choose another seed")
        if not found:
            candidates *= 4  # nobody ends so early: look further
            continue
        before = len(chosen)
        x, w, held = np.array([r["x"] for r in found]), np.array([r["w"] for r in found]), np.array([r["clock"] for r in found])
        while len(chosen) < k:
            ends, _ = clock_ends(x, w, held, np.array(chosen), np.array(times))
            i = int(ends.argmin())
            if not ends[i] <= until:
                break
            chosen.append([float(v) for v in x[i]])
            times.append(float(ends[i]))
        if len(chosen) == before:
            candidates *= 4
    return list(enumerate(chosen))


def clock_ends(x: np.ndarray, w: np.ndarray, clock: np.ndarray, centers: np.ndarray, times: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """When each point's clock ends if no center follows those of ``times``, and its rate now."""
    d2 = np.empty((len(x), len(centers)))
    for j, c in enumerate(centers):
        diff = x - c
        d2[:, j] = np.einsum("ij,ij->i", diff, diff)
    rate = np.minimum.accumulate(d2, axis=1) * w[:, None]
    spent = rate[:, :-1] @ np.diff(times)
    now = rate[:, -1]
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(now > 0, times[-1] + (clock - spent) / now, np.inf), now


def kmeanspp(pts: DataFrame, k: int, seed: int = 1, max_iter: int = 20, tol: float = 1e-4) -> tuple[list, list[float]]:
    """Squared-distance seeding (by the race) and Lloyd on the full table: a few scans and one for each iteration."""
    return lloyd(pts, race_seeds(pts, k, seed), max_iter, tol)


def seed_array(x: np.ndarray, w: np.ndarray, k: int, rng, how: str = "d2") -> np.ndarray:
    """Seeds of a weighted array; fewer where there are fewer distinct points."""
    if how == "uniform":
        return x[rng.choice(len(x), min(k, len(x)), replace=False, p=w / w.sum())]
    first = int(rng.choice(len(x), p=w / w.sum()))
    c, d2 = [x[first]], ((x - x[first]) ** 2).sum(1)
    while len(c) < k:
        p = w * d2
        total = p.sum()
        if total <= 0:
            break
        i = int(rng.choice(len(x), p=p / total))
        c.append(x[i])
        d2 = np.minimum(d2, ((x - x[i]) ** 2).sum(1))
    return np.array(c)


def lloyd_array(x: np.ndarray, w: np.ndarray, c: np.ndarray, max_iter: int = 100, tol: float = 1e-6) -> tuple[np.ndarray, float]:
    """Lloyd on a weighted array."""
    last = np.inf
    for _ in range(max_iter):
        d2 = block_distances(x, c)
        k = d2.argmin(1)
        cost = float((w * d2[np.arange(len(x)), k]).sum())
        total = np.bincount(k, w, len(c))
        sums = np.zeros_like(c)
        np.add.at(sums, k, x * w[:, None])
        full = total > 0
        c = c.copy()
        c[full] = sums[full] / total[full, None]
        if last - cost <= tol * last if np.isfinite(last) else False:
            break
        last = cost
    return c, float((w * block_distances(x, c).min(1)).sum())


def kmeanspp_array(x: np.ndarray, w: np.ndarray, k: int, seed, restarts: int = 1, how: str = "d2") -> tuple[np.ndarray, float]:
    best = None
    for r in range(restarts):
        rng = np.random.default_rng([seed, r])
        found = lloyd_array(x, w, seed_array(x, w, k, rng, how))
        if best is None or found[1] < best[1]:
            best = found
    return best


def kmeanspp_runs(summary: DataFrame, k: int, restarts: int = 5, seed: int = 1, how: str = "d2") -> DataFrame:
    """All restarts on a weighted summary, each in its own task: ``run, cost, centers``.

    The summary has a bounded size (it is sent to every restart); more rows than
    ``SUMMARY_ROWS`` are refused.
    """
    spark = summary.sparkSession
    ship_package(spark)
    rows = summary.select("id", F.col("x").cast("array<double>").alias("x"), F.col("w").cast("bigint").alias("w"))
    runs = spark.range(restarts).select(F.col("id").cast("int").alias("run"))

    def solve(key, table):
        if table.num_rows > SUMMARY_ROWS:
            raise ValueError("summary too large for one task: reduce it first")
        x, w = to_matrix(table.column("x")), table.column("w").to_numpy().astype(float)
        order = np.lexsort(tuple(x.T[::-1]))
        run = int(key[0].as_py())
        c, cost = kmeanspp_array(x[order], w[order], k, [seed, run], 1, how)
        c = c[np.lexsort(tuple(c.T[::-1]))]
        return pa.table({"run": pa.array([run], pa.int32()), "cost": pa.array([cost]), "centers": pa.array([c.tolist()], pa.list_(pa.list_(pa.float64())))})

    return rows.crossJoin(F.broadcast(runs)).groupBy("run").applyInArrow(solve, "run int, cost double, centers array<array<double>>")


def kmeanspp_summary(summary: DataFrame, k: int, restarts: int = 5, seed: int = 1, how: str = "d2") -> DataFrame:
    """Centers ``run, cid, c, cost`` of the best restart on a summary."""
    best = kmeanspp_runs(summary, k, restarts, seed, how).agg(F.min_by(F.struct("run", "cost", "centers"), F.struct("cost", "run")).alias("b"))
    return best.select("b.run", "b.cost", F.posexplode("b.centers").alias("cid", "c")).select("run", F.col("cid").cast("int").alias("cid"), "c", "cost")


def center_rows(centers: DataFrame) -> list:
    return [(r["cid"], list(r["c"])) for r in centers.select("cid", "c").orderBy("cid").collect()]


def library_kmeans(pts: DataFrame, k: int, seed: int = 1) -> list:
    """Second opinion: the k-means|| of Spark's own library."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = weighted(pts).select(array_to_vector(F.col("x").cast("array<double>")).alias("features"), F.col("w").cast("double").alias("w"))
    model = KMeans(k=k, seed=seed, initMode="k-means||", weightCol="w", maxIter=20).fit(rows)
    return [(i, [float(v) for v in c]) for i, c in enumerate(model.clusterCenters())]


def agreement(assigned: DataFrame, label: str = "label") -> DataFrame:
    """Purity and pair counts of a clustering against given labels, from one cid × label table."""
    table = assigned.groupBy("cid", label).agg(F.count("*").alias("n"))
    pair = F.sum(F.col("n") * (F.col("n") - 1) / 2)
    by_cid = table.groupBy("cid").agg(F.max("n").alias("top"), F.sum("n").alias("n"))
    by_label = table.groupBy(label).agg(F.sum("n").alias("n"))
    one = by_cid.agg((F.sum("top") / F.sum("n")).alias("purity"), pair.cast("bigint").alias("pairs_cluster"))
    return one.crossJoin(by_label.agg(pair.cast("bigint").alias("pairs_label"))).crossJoin(table.agg(pair.cast("bigint").alias("pairs_both")))


__all__ = ["Window", "agreement", "center_rows", "centers_frame", "d2_seeds", "kmeanspp", "kmeanspp_runs", "kmeanspp_summary", "library_kmeans", "lloyd", "race_seeds", "uniform_seeds"]
