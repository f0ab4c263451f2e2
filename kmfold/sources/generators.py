"""Generated point sets whose coordinates an arithmetic hash gives, so that SQL can rebuild them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kmfold.functions.hashing import arithmetic_hash, uniform

#: Half-widths of signal and noise, scales of outer and inner simplices.
SIGNAL, NOISE, OUTER, INNER = 10.0, 0.5, 1000.0, 100.0


def _spread(key: Column, seed: int, half: float | Column) -> Column:
    return (uniform(key, seed) * 2.0 - 1.0) * half


def uniform_cube(spark: SparkSession, n: int, d: int, half: float = SIGNAL, seed: int = 3) -> DataFrame:
    """``n`` points uniform in a cube of ``d`` dimensions."""
    x = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: _spread(F.col("id") * d + j, seed, half))
    return spark.range(n).select("id", x.alias("x"), F.lit(1).cast("bigint").alias("w"))


def block_signal(spark: SparkSession, blocks: int, y: int, d: int, x: int = 100, seed: int = 5, signal: float = SIGNAL, noise: float = NOISE) -> DataFrame:
    """Blocks of ``y`` points with ``x`` coordinates of signal, chosen anew for each block, and noise in the others.

    The chosen ones are those of least hash within a block: exactly ``x`` of them.
    """
    marks = spark.range(blocks).select(F.col("id").alias("block"), F.posexplode(F.array_sort(F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: F.struct(arithmetic_hash(F.col("id") * d + j, seed + 1).alias("h"), j.alias("j"))))).alias("rank", "s"))
    chosen = marks.filter(F.col("rank") < x).groupBy("block").agg(F.array_sort(F.collect_list(F.col("s.j"))).alias("dims"))
    rows = spark.range(blocks * y).withColumn("block", F.expr(f"id div {y}"))
    value = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: _spread(F.col("id") * d + j, seed, F.when(F.array_contains(F.col("dims"), j), signal).otherwise(noise)))
    # the table of chosen coordinates has one row a block
    return rows.join(F.broadcast(chosen), "block").select("id", value.alias("x"), F.lit(1).cast("bigint").alias("w"), F.col("block").cast("int").alias("label"))


def nested_simplex(spark: SparkSession, k: int, n: int, outer: float = OUTER, inner: float = INNER, sparse: bool = False) -> DataFrame:
    """``k`` vertices of a simplex, each carrying a simplex of ``n/k`` points in dimensions of its own.

    ``inner`` is the side length, so the optimum is k(n/k − 1)·inner²/2. The sparse
    form has the positions and values of the two non-zeros of each row.
    """
    if n % k:
        raise ValueError("n must be a multiple of k")
    return simplex_rows(spark.range(n), k, n, outer, inner, sparse)


def simplex_rows(ids: DataFrame, k: int, n: int = 0, outer: float = OUTER, inner: float = INNER, sparse: bool = False) -> DataFrame:
    """The same over given ids, ``k`` classes by remainder; the dense form takes ids below ``n``, the sparse form any."""
    rows = ids.withColumn("label", F.pmod("id", F.lit(k)).cast("int"))
    leg = inner / 2**0.5
    if sparse:
        return rows.select("id", F.array(F.col("label").cast("bigint"), F.lit(k) + F.col("id")).alias("pos"), F.array(F.lit(outer), F.lit(leg)).alias("val"), F.lit(1).cast("bigint").alias("w"), "label")
    x = F.transform(F.sequence(F.lit(0), F.lit(k + n - 1)), lambda j: F.when(j == F.col("label"), outer).when(j == F.col("id").cast("int") + k, leg).otherwise(0.0))
    return rows.select("id", x.alias("x"), F.lit(1).cast("bigint").alias("w"), "label")


def simplex_optimum(k: int, n: int, inner: float = INNER) -> float:
    return k * (n / k - 1) * inner**2 / 2


def one_center_cost_block(n: int, d: int, x: int = 100, signal: float = SIGNAL, noise: float = NOISE) -> float:
    """Expected cost of the origin as the only center of block-signal data."""
    return n * (x * signal**2 / 3 + (d - x) * noise**2 / 3)


def one_center_cost_cube(n: int, d: int, half: float = SIGNAL) -> float:
    return n * d * half**2 / 3


def words(spark: SparkSession, n: int, d: int, topics: int = 4, seed: int = 11) -> DataFrame:
    """Sparse non-negative counts with a few heavy directions, like a bag of words."""
    topic = F.pmod("id", F.lit(topics))
    x = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: F.floor(uniform(F.col("id") * d + j, seed) * F.when(F.pmod(j, F.lit(topics)) == topic, 12.0 / (1 + j / topics)).otherwise(1.2)))
    return spark.range(n).select("id", F.transform(x, lambda v: v.cast("double")).alias("x"), F.lit(1).cast("bigint").alias("w"), topic.cast("int").alias("label"))
