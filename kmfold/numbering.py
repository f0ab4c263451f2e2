"""Gapless numbers and order-preserving buckets without a one-task window."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kmfold.staging import shuffle_partitions

FAN = 256


def number_within(df: DataFrame, groups: list[str], order: list[str], out: str, salts: int | None = None) -> DataFrame:
    """Number the rows of each group from 0 without gaps.

    Every group is dealt over ``salts`` sub-groups by a hash of the order
    columns, so a group with a third of all rows is still spread over the
    cluster; the sub-groups' counts give each one its first number. ``df`` is
    read twice: stage it first when it is costly.
    """
    salts = salts or 8 * shuffle_partitions(df.sparkSession)
    salted = df.withColumn("_salt", F.pmod(F.xxhash64(*order), F.lit(salts)).cast("int"))
    counts = salted.groupBy(*groups, "_salt").agg(F.count("*").alias("_n"))
    running = Window.partitionBy(*groups).orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    firsts = counts.withColumn("_first", F.coalesce(F.sum("_n").over(running), F.lit(0))).drop("_n")
    inner = Window.partitionBy(*groups, "_salt").orderBy(*order)
    numbered = salted.withColumn("_at", F.row_number().over(inner).cast("long") - 1)
    joined = numbered.join(firsts, [*groups, "_salt"])
    return joined.withColumn(out, F.col("_first") + F.col("_at")).drop("_salt", "_first", "_at")


def range_bounds(df: DataFrame, col: str, buckets: int) -> list:
    """At most ``buckets - 1`` increasing cut values of ``col`` (a bounded driver result)."""
    if buckets < 2:
        return []
    shares = [i / buckets for i in range(1, buckets)]
    row = df.agg(F.percentile_approx(col, shares, max(10_000, 20 * buckets)).alias("q")).first()
    return sorted(set(row["q"] or []))


def bucket_of(col: Column, bounds: list) -> Column:
    """Index of the range that holds ``col``: 0 up to ``len(bounds)``, in order."""
    if not bounds:
        return F.lit(0)
    if len(bounds) > FAN:  # a coarse search over every FAN-th cut, then a count inside one group
        groups = [bounds[i : i + FAN] for i in range(0, len(bounds), FAN)]
        coarse = bucket_of(col, [g[-1] for g in groups[:-1]])
        table = F.array(*[F.array(*map(F.lit, g)) for g in groups])
        inside = F.size(F.filter(F.element_at(table, coarse + 1), lambda b: b < col))
        return (coarse * FAN + inside).cast("int")

    def pick(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(col <= F.lit(bounds[mid]), pick(lo, mid)).otherwise(pick(mid + 1, hi))

    return pick(0, len(bounds))
