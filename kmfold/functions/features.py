"""Clustering features: weight, vector sum and sum of squared lengths of a point set.

Features add up, so they are aggregated with map-side combining and merged at will;
the cost of a set against one center follows from its feature alone.
"""

from __future__ import annotations

from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kmfold.functions.vectors import dot, scale, squared_length


def cf_of(x: Column | str = "x", w: Column | str = "w") -> Column:
    """Feature of ``w`` copies of one point."""
    x, w = (F.col(c) if isinstance(c, str) else c for c in (x, w))
    return F.struct(w.cast("bigint").alias("w"), scale(x, w.cast("double")).alias("ls"), (w * squared_length(x)).alias("ss"))


def cf_agg(pts: DataFrame, by: list[str] | None = None, x: str = "x", w: str = "w") -> DataFrame:
    """Feature of every group of points: columns ``by`` and ``cf``.

    The vector sum is the summarizer's, an object-hash aggregate with partial sums.
    """
    by = by or []
    v = array_to_vector(F.col(x).cast("array<double>"))
    rows = pts.select(*by, v.alias("_v"), F.col(w).cast("double").alias("_w"), F.col(w).cast("bigint").alias("_n"), (F.col(w) * squared_length(F.col(x).cast("array<double>"))).alias("_ss"))
    out = rows.groupBy(*by).agg(F.sum("_n").alias("_n"), Summarizer.sum(F.col("_v"), F.col("_w")).alias("_ls"), F.sum("_ss").alias("_ss"))
    return out.select(*by, F.struct(F.col("_n").alias("w"), vector_to_array("_ls").alias("ls"), F.col("_ss").alias("ss")).alias("cf"))


def cf_merge(features: DataFrame, by: list[str] | None = None, cf: str = "cf") -> DataFrame:
    """Feature of the union of the sets of each group: a sum, member by member."""
    by = by or []
    rows = features.select(*by, F.col(f"{cf}.w").alias("_n"), array_to_vector(F.col(f"{cf}.ls")).alias("_ls"), F.col(f"{cf}.ss").alias("_ss"))
    out = rows.groupBy(*by).agg(F.sum("_n").alias("_n"), Summarizer.sum(F.col("_ls")).alias("_ls"), F.sum("_ss").alias("_ss"))
    return out.select(*by, F.struct(F.col("_n").alias("w"), vector_to_array("_ls").alias("ls"), F.col("_ss").alias("ss")).alias("cf"))


def centroid_of(cf: Column) -> Column:
    return scale(cf["ls"], 1.0 / cf["w"].cast("double"))


def centroid(pts: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Weighted mean of each group."""
    by = by or []
    return cf_agg(pts, by).select(*by, F.col("cf.w").alias("w"), centroid_of(F.col("cf")).alias("x"))


def cf_cost(cf: Column, c: Column) -> Column:
    """Sum of squared distances of the set to one center."""
    return cf["ss"] - 2.0 * dot(cf["ls"], c) + cf["w"] * squared_length(c)


def cf_within(cf: Column) -> Column:
    """Sum of squared distances to the set's own centroid, never below 0."""
    return F.greatest(F.lit(0.0), cf["ss"] - squared_length(cf["ls"]) / cf["w"])


def insert_increase(s: Column, w: Column, dist2: Column, mode: str = "exact") -> Column:
    """Rise of a feature's cost when ``w`` copies join its ``s`` members at ``dist2`` from the centroid.

    ``naive`` is the overestimate that leaves the centroid where it was.
    """
    if mode == "naive":
        return w * dist2
    return s.cast("double") * w / (s + w) * dist2


def max_copies(w: Column, s: Column, c: Column, dist2: Column, limit: Column) -> Column:
    """Most copies (a whole number up to ``w``) that keep a feature's cost within ``limit``."""
    slack = s * dist2 - limit + c
    fit = F.floor((s * limit - s * c) / slack).cast("bigint")
    return F.when(slack <= 0, w.cast("bigint")).otherwise(F.greatest(F.lit(0).cast("bigint"), F.least(w.cast("bigint"), fit)))
