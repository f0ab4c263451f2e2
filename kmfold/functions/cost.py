"""Nearest centers and the objective, without joining points to centers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kmfold.functions.vectors import squared_distance
from kmfold.staging import ship_package

#: Above so many center coordinates the expression form gives way to the vectorized one.
LITERAL_COORDINATES = 512
BROADCAST_COORDINATES = 40_000_000


def center_list(centers: DataFrame) -> list[tuple[int, list[float]]]:
    """Centers ``cid, c`` on the driver: k rows, checked against a bound on their number and one on their coordinates."""
    most = BROADCAST_COORDINATES // 64
    rows = centers.select("cid", "c").orderBy("cid").limit(most + 1).collect()
    if len(rows) > most or sum(len(r["c"]) for r in rows) > BROADCAST_COORDINATES:
        raise ValueError("too many centers or center coordinates to send to every task: assign against blocks of centers")
    return [(int(r["cid"]), [float(v) for v in r["c"]]) for r in rows]


def check_centers(centers: list) -> None:
    """Refuse more centers or coordinates than every task can hold."""
    if len(centers) > BROADCAST_COORDINATES // 64 or sum(len(c) for _, c in centers) > BROADCAST_COORDINATES:
        raise ValueError("too many centers or center coordinates to send to every task: assign against blocks of centers")


def _literal(centers: list[tuple[int, list[float]]]) -> Column:
    return F.array(*[F.struct(F.lit(cid).cast("int").alias("cid"), F.array(*map(F.lit, c)).alias("c")) for cid, c in centers])


def nearest(x: Column, centers: Column) -> Column:
    """Struct ``d2, cid`` of the nearest center, ties to the smaller cid; a narrow expression."""
    return F.array_min(F.transform(centers, lambda c: F.struct(squared_distance(x, c["c"]).alias("d2"), c["cid"].alias("cid"))))


def assign(pts: DataFrame, centers: DataFrame | list, vectorized: bool | None = None) -> DataFrame:
    """Add ``cid`` and ``d2`` to every point."""
    held = centers if isinstance(centers, list) else center_list(centers)
    if not held:
        raise ValueError("no centers")
    check_centers(held)
    n = sum(len(c) for _, c in held)
    if vectorized is None:
        vectorized = n > LITERAL_COORDINATES
    if vectorized:
        from kmfold.functions.sqlapi import assign_udf

        ship_package(pts.sparkSession)
        near = assign_udf(held)(F.col("x").cast("array<double>"))
    else:
        one = pts.sparkSession.range(1).select(_literal(held).alias("_centers"))
        pts = pts.join(F.broadcast(one), how="cross")  # a single row of bounded size
        near = nearest(F.col("x").cast("array<double>"), F.col("_centers"))
    out = pts.withColumn("_near", near).withColumn("cid", F.col("_near.cid")).withColumn("d2", F.col("_near.d2"))
    return out.drop("_near", "_centers")


def kmeans_cost(pts: DataFrame, centers: DataFrame | list, vectorized: bool | None = None) -> DataFrame:
    """One row: the weighted sum of squared distances to the nearest center, points and weight."""
    w = "w" if "w" in pts.columns else None
    rows = assign(pts, centers, vectorized)
    weight = F.col(w).cast("double") if w else F.lit(1.0)
    return rows.agg(F.sum(weight * F.col("d2")).alias("cost"), F.count("*").alias("n"), F.sum(weight.cast("bigint")).alias("weight"))


def cost_value(pts: DataFrame, centers: DataFrame | list) -> float:
    return float(kmeans_cost(pts, centers, vectorized=True).first()["cost"])


def panel_costs(pts: DataFrame, panel: list[tuple[int, list]]) -> DataFrame:
    """Cost of several center sets in one scan: ``panel, cost``. The panel is bounded like centers are."""
    w = F.col("w").cast("double") if "w" in pts.columns else F.lit(1.0)
    from kmfold.functions.sqlapi import panel_udf

    ship_package(pts.sparkSession)
    near = panel_udf([c for _, c in panel])(F.col("x").cast("array<double>"))
    sums = pts.select(w.alias("_w"), near.alias("_d2")).agg(*[F.sum(F.col("_w") * F.col("_d2")[i]).alias(f"c{i}") for i in range(len(panel))])
    return sums.select(F.explode(F.array(*[F.struct(F.lit(p).alias("panel"), F.col(f"c{i}").alias("cost")) for i, (p, _) in enumerate(panel)])).alias("r")).select("r.*")
