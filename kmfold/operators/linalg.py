"""Best-fit subspaces: decompositions of one piece, and of a whole table.

Rows are points. A projection stays in the original coordinates; only its intrinsic
dimension falls. Integral weights act as copies: rows are scaled by the root of the
weight before the decomposition and back afterwards.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kmfold.functions.arrays import to_column, to_matrix
from kmfold.staging import ship_package

KINDS = ("exact", "gram", "random", "random2", "none")
GRAM_DIMENSIONS = 4000


def svd_exact(a: np.ndarray, l: int) -> tuple[np.ndarray, np.ndarray]:  # noqa: E741
    """Singular values and right vectors (rows) of the full decomposition, cut to ``l``."""
    _, s, vt = np.linalg.svd(a, full_matrices=False)
    return s[:l], vt[:l]


def svd_truncated(a: np.ndarray, l: int) -> tuple[np.ndarray, np.ndarray]:  # noqa: E741
    """Through the smaller Gram matrix; falls back to the full way where squaring loses the small values."""
    n, d = a.shape
    g = a.T @ a if d <= n else a @ a.T
    val, vec = np.linalg.eigh(g)
    val, vec = val[::-1][:l], vec[:, ::-1][:, :l]
    s = np.sqrt(np.maximum(val, 0.0))
    if len(s) and s[0] > 0 and s[-1] / s[0] < 1e-7:
        return svd_exact(a, l)
    if d <= n:
        return s, vec.T
    return s, (a.T @ vec / np.where(s > 0, s, 1.0)).T


def svd_random(a: np.ndarray, l: int, seed=0, oversample: int = 10, power: int = 2, two_sided: bool = False) -> tuple[np.ndarray, np.ndarray]:  # noqa: E741
    """A sketch of the column space finds the subspace; ``two_sided`` sketches the rows as well before the small decomposition."""
    n, d = a.shape
    k = min(l + oversample, n, d)
    rng = np.random.default_rng(seed)
    if two_sided:
        # rows first: the row space of a random mix of rows
        q, _ = np.linalg.qr((rng.standard_normal((k, n)) @ a).T)
        for _ in range(power):
            q, _ = np.linalg.qr(a.T @ (a @ q))
        z = a @ q
        p, _ = np.linalg.qr(z @ rng.standard_normal((q.shape[1], q.shape[1])))
        _, s, wt = np.linalg.svd(p.T @ z, full_matrices=False)
        return s[:l], (wt @ q.T)[:l]
    y = a @ rng.standard_normal((d, k))
    for _ in range(power):
        y, _ = np.linalg.qr(y)
        y = a @ (a.T @ y)
    q, _ = np.linalg.qr(y)
    _, s, vt = np.linalg.svd(q.T @ a, full_matrices=False)
    return s[:l], vt[:l]


def decompose(a: np.ndarray, l: int, kind: str = "random", seed=0) -> tuple[np.ndarray, np.ndarray]:  # noqa: E741
    if kind == "exact":
        return svd_exact(a, l)
    if kind == "gram":
        return svd_truncated(a, l)
    if kind in ("random", "random2"):
        return svd_random(a, l, seed, two_sided=kind == "random2")
    raise ValueError(f"kind must be one of {KINDS}")


def project_matrix(x: np.ndarray, l: int, w: np.ndarray | None = None, kind: str = "random", seed=0, center: bool = False) -> tuple[np.ndarray, float]:  # noqa: E741
    """Rows in their best-fit subspace of dimension ``l``, and the weighted squared movement.

    Where ``l`` reaches the rank's bound nothing can be gained and nothing is computed.
    """
    n, d = x.shape
    if kind == "none" or l >= min(n, d) or not n:
        return x, 0.0
    mean = np.average(x, axis=0, weights=w) if center else 0.0
    a = x - mean
    root = np.sqrt(w.astype(float))[:, None] if w is not None else 1.0
    _, v = decompose(a * root, l, kind, seed)
    out = (a @ v.T) @ v + mean
    moved = (out - x) ** 2
    return out, float((moved.sum(1) * (w if w is not None else 1.0)).sum())


def coordinates(x: np.ndarray, l: int, kind: str = "exact", seed=0) -> tuple[np.ndarray, np.ndarray]:  # noqa: E741
    """The ``l`` coordinates of each row and the basis (valid inside one piece only)."""
    _, v = decompose(x, min(l, *x.shape), kind, seed)
    return x @ v.T, v


def target_dim(k: int, n: int | None = None, d: int | None = None, eps: float | None = None, rule: str = "1.5k") -> int:
    """Dimension to project to: ``k`` (factor 2), ``1.5k`` (often enough) or ``k/eps`` (factor 1+eps), never above n or d."""
    if rule == "k/eps":
        if not eps:
            raise ValueError("k/eps needs eps")
        l = math.ceil(k / eps)  # noqa: E741
    else:
        l = {"k": k, "1.5k": math.ceil(1.5 * k)}[rule]  # noqa: E741
    return max(1, min([l, *(v for v in (n, d) if v)]))


def project(pts: DataFrame, l: int, by: str = "piece", kind: str = "random", seed: int = 0, emit: str = "rows") -> DataFrame:  # noqa: E741
    """Project each piece on its own subspace. ``emit='coords'`` keeps l coordinates and the basis."""
    ship_package(pts.sparkSession)

    def run(key, table):
        table = table.sort_by("id")
        x, w = to_matrix(table.column("x")), table.column("w").to_numpy()
        piece = int(key[0].as_py())
        if emit == "coords":
            y, v = coordinates(x, l, kind, [seed, piece])
            basis = to_column(np.repeat(v.reshape(1, -1), len(x), axis=0))
            return pa.table({"id": table.column("id").cast(pa.int64()), "x": to_column(y), "w": pa.array(w, pa.int64()), by: pa.array([piece] * len(x), pa.int64()), "basis": basis})
        y, moved = project_matrix(x, l, w, kind, [seed, piece])
        return pa.table({"id": table.column("id").cast(pa.int64()), "x": to_column(y), "w": pa.array(w, pa.int64()), by: pa.array([piece] * len(x), pa.int64()), "moved": pa.array([moved / len(x)] * len(x))})

    last = "basis array<double>" if emit == "coords" else "moved double"
    return pts.select("id", "x", F.col("w").cast("bigint").alias("w"), F.col(by).cast("bigint").alias(by)).groupBy(by).applyInArrow(run, f"id bigint, x array<double>, w bigint, {by} bigint, {last}")


def gram_rows(pts: DataFrame) -> DataFrame:
    """Rows ``i, g`` of the weighted Gram matrix: a d×d sum for each partition, then one sum by row."""
    ship_package(pts.sparkSession)

    def run(batches):
        total = None
        for b in batches:
            if b.num_rows:
                x, w = to_matrix(b.column(0)), b.column(1).to_numpy()
                g = (x * w[:, None]).T @ x
                total = g if total is None else total + g
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total)), pa.int32()), to_column(total)], ["i", "g"])

    w = F.col("w") if "w" in pts.columns else F.lit(1)
    parts = pts.select(F.col("x").cast("array<double>").alias("x"), w.cast("double").alias("w")).mapInArrow(run, "i int, g array<double>")
    return parts.groupBy("i").agg(vector_to_array(Summarizer.sum(array_to_vector("g"))).alias("g"))


def triangle(pts: DataFrame) -> np.ndarray:
    """The triangular factor of a whole table: d×d numbers on the driver, with nothing squared.

    The table is this factor behind orthonormal columns, so both have the same singular
    values, right vectors, residuals and, from one random matrix, sketched subspaces.
    Partitions fold batch by batch, then eight tasks and one fold what is left.
    """
    ship_package(pts.sparkSession)

    def run(batches):
        r = None
        for b in batches:
            if b.num_rows:
                x = to_matrix(b.column(0))
                r = np.linalg.qr(x if r is None else np.vstack([r, x]), mode="r")
        if r is not None:
            yield pa.RecordBatch.from_arrays([to_column(r)], ["x"])

    out = pts.select(F.col("x").cast("array<double>").alias("x")).mapInArrow(run, "x array<double>")
    for parts in (8, 1):
        out = out.repartition(parts).mapInArrow(run, "x array<double>")
    return np.array([r["x"] for r in out.collect()])


def gram_matrix(pts: DataFrame) -> np.ndarray:
    """The Gram matrix on the driver: d×d numbers, for d up to ``GRAM_DIMENSIONS``."""
    d = pts.select(F.size("x").alias("d")).first()
    if d is None:
        return np.zeros((0, 0))
    if d["d"] > GRAM_DIMENSIONS:
        raise ValueError("dimension too high for a Gram matrix: use global_basis(method='sketch')")
    return np.array([r["g"] for r in gram_rows(pts).orderBy("i").collect()])


def global_basis(pts: DataFrame, l: int, method: str = "gram", seed: int = 0, oversample: int = 10) -> tuple[np.ndarray, np.ndarray]:  # noqa: E741
    """Singular values and best-fit subspace of a whole table: by the Gram matrix, or by a sketch of d×(l+p) numbers."""
    if method == "gram":
        val, vec = np.linalg.eigh(gram_matrix(pts))
        return np.sqrt(np.maximum(val[::-1][:l], 0.0)), vec[:, ::-1][:, :l].T
    d = pts.select(F.size("x").alias("d")).first()["d"]
    q = np.linalg.qr(np.random.default_rng(seed).standard_normal((d, min(d, l + oversample))))[0]
    for _ in range(2):
        y = _gram_times(pts, q)
        q = np.linalg.qr(y)[0]
    small = q.T @ _gram_times(pts, q)
    val, vec = np.linalg.eigh((small + small.T) / 2)
    return np.sqrt(np.maximum(val[::-1][:l], 0.0)), (q @ vec[:, ::-1][:, :l]).T


def _gram_times(pts: DataFrame, q: np.ndarray) -> np.ndarray:
    """AᵀAQ in one pass: partition sums of d×k numbers, added by row."""
    ship_package(pts.sparkSession)
    held = pts.sparkSession.sparkContext.broadcast(q)

    def run(batches):
        total = None
        for b in batches:
            if b.num_rows:
                x, w = to_matrix(b.column(0)), b.column(1).to_numpy()
                y = (x * w[:, None]).T @ (x @ held.value)
                total = y if total is None else total + y
        if total is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total)), pa.int32()), to_column(total)], ["i", "g"])

    w = F.col("w") if "w" in pts.columns else F.lit(1)
    parts = pts.select(F.col("x").cast("array<double>").alias("x"), w.cast("double").alias("w")).mapInArrow(run, "i int, g array<double>")
    rows = parts.groupBy("i").agg(vector_to_array(Summarizer.sum(array_to_vector("g"))).alias("g")).orderBy("i").collect()
    return np.array([r["g"] for r in rows])


def project_global(pts: DataFrame, v: np.ndarray) -> DataFrame:
    """All rows in one given subspace (basis of bounded size)."""
    ship_package(pts.sparkSession)
    held = pts.sparkSession.sparkContext.broadcast(v)

    def run(batches):
        for b in batches:
            if b.num_rows:
                y = (to_matrix(b.column(1)) @ held.value.T) @ held.value
                yield pa.RecordBatch.from_arrays([b.column(0), to_column(y), b.column(2)], ["id", "x", "w"])

    return pts.select(F.col("id").cast("bigint").alias("id"), F.col("x").cast("array<double>").alias("x"), F.col("w").cast("bigint").alias("w")).mapInArrow(run, "id bigint, x array<double>, w bigint")


def spectrum(pts: DataFrame, top: int | None = None) -> DataFrame:
    """``rank, sigma, energy_cum``: singular values of a table and the share of energy up to each."""
    val = np.linalg.eigvalsh(gram_matrix(pts))[::-1]
    s = np.sqrt(np.maximum(val, 0.0))
    rows = pts.sparkSession.createDataFrame([(i + 1, float(v)) for i, v in enumerate(s)], "rank int, sigma double")
    upto = Window.orderBy("rank").rowsBetween(Window.unboundedPreceding, Window.currentRow)  # d rows
    total = float((s * s).sum()) or 1.0
    out = rows.withColumn("energy_cum", F.sum(F.col("sigma") * F.col("sigma")).over(upto) / total)
    return out.filter(F.col("rank") <= top) if top else out


def residual(a: np.ndarray, v: np.ndarray) -> float:
    """Squared Frobenius distance of a matrix to its projection on the rows of ``v``."""
    r = a - (a @ v.T) @ v
    return float((r * r).sum())


def svd_comparison(a: np.ndarray, l: int, seeds, kind: str = "random", reference_rank: int | None = None) -> list[dict]:  # noqa: E741
    """Deviation of a sketched subspace from the exact one, for each seed, with CPU seconds of both.

    Two forms are told apart: against the exact residual of the same rank (never
    negative) and against that of a fixed rank, each squared and as a root.
    """
    import time

    t = time.process_time()
    _, s, vt = np.linalg.svd(a, full_matrices=False)
    exact_s = time.process_time() - t
    own = float((s[l:] ** 2).sum())
    fixed = float((s[(reference_rank or l) :] ** 2).sum())
    out = []
    for seed in seeds:
        t = time.process_time()
        _, v = decompose(a, l, kind, seed)
        took = time.process_time() - t
        r = residual(a, v)
        out.append({
            "l": l, "seed": int(seed), "exact_residual": own, "random_residual": r,
            "percent": 100.0 * (r - own) / own if own else 0.0, "percent_fixed": 100.0 * (r - fixed) / fixed if fixed else 0.0,
            "percent_root": 100.0 * (math.sqrt(r / own) - 1) if own else 0.0, "percent_fixed_root": 100.0 * (math.sqrt(r / fixed) - 1) if fixed else 0.0,
            "exact_cpu_s": exact_s, "random_cpu_s": took,
        })
    return out
