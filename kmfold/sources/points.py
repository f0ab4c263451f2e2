"""Point tables ``id, x, w`` from the given tables."""

from __future__ import annotations


from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kmfold.plans.pieces import dense_index

LINE_ORDER = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate", "l_returnflag", "l_linestatus"]
TOKEN = "[^a-z0-9]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def points_from(df: DataFrame, key: str | Column, x: str | Column, w: str | Column | None = None, on_invalid: str = "error", keep: list[str] | None = None) -> DataFrame:
    """Contract ``id, x, w``: null or non-finite coordinates, and weights below 1 or not whole, are refused or dropped."""
    as_col = lambda c: F.col(c) if isinstance(c, str) else c
    weight = as_col(w) if w is not None else F.lit(1)
    rows = df.select(as_col(key).cast("bigint").alias("id"), as_col(x).cast("array<double>").alias("x"), weight.cast("double").alias("_w"), *(keep or []))
    fine = F.col("x").isNotNull() & F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))) & (F.col("_w") >= 1) & (F.col("_w") == F.floor("_w"))
    fine = F.coalesce(fine, F.lit(False))
    if on_invalid == "drop":
        rows = rows.filter(fine)
    elif on_invalid == "error":
        rows = rows.withColumn("x", F.when(fine, F.col("x")).otherwise(F.raise_error(F.lit("a point has a null or non-finite coordinate or a weight that is not a positive whole number"))))
    else:
        raise ValueError("on_invalid must be error or drop")
    return rows.withColumn("w", F.col("_w").cast("bigint")).select("id", "x", "w", *(keep or []))


def dimension(pts: DataFrame) -> int:
    """The common length of all vectors; ragged tables are refused."""
    r = pts.agg(F.min(F.size("x")).alias("a"), F.max(F.size("x")).alias("b")).first()
    if r["a"] != r["b"]:
        raise ValueError(f"vectors of {r['a']} to {r['b']} coordinates")
    return int(r["a"] or 0)


def emb64(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = table(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label")
    return df.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("x"), F.lit(1).cast("bigint").alias("w"), "label")


def _line(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(*LINE_ORDER)


def line_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four measures as columns f0..f3: scalar aggregates stay in generated code."""
    q, p, d, t = "l_quantity", "l_extendedprice", "l_discount", "l_tax"
    return _line(spark, sf_dir).select(F.col(q).alias("f0"), (F.col(p) / 1000).alias("f1"), (F.col(d) * 100).alias("f2"), (F.col(t) * 100).alias("f3"), "l_returnflag", "l_linestatus")


def _numbered_line(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dense_index(_line(spark, sf_dir), LINE_ORDER)


def _measures() -> list[Column]:
    return [F.col("l_quantity"), F.col("l_extendedprice") / 1000, F.col("l_discount") * 100, F.col("l_tax") * 100]


def line4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _numbered_line(spark, sf_dir).select("id", F.array(*_measures()).alias("x"), F.lit(1).cast("bigint").alias("w"))


def hashed(key: Column, buckets: int, scale: float) -> list[Column]:
    """One-hot of a key's hash."""
    h = F.pmod(key * 2654435761, F.lit(buckets))
    return [F.when(h == b, scale).otherwise(0.0) for b in range(buckets)]


def line_vectors(d: int) -> list[Column]:
    """Measures, flags, month and hashed keys as ``d`` coordinates (32 or more)."""
    cols = _measures()
    cols += [F.when(F.col("l_returnflag") == v, 10.0).otherwise(0.0) for v in ("A", "N", "R")]
    cols += [F.when(F.col("l_linestatus") == v, 10.0).otherwise(0.0) for v in ("F", "O")]
    month = F.month("l_shipdate")
    cols += [F.when(F.floor((month - 1) / 3) == q, 5.0).otherwise(0.0) for q in range(4)]
    rest = d - len(cols)
    cols += hashed(F.col("l_suppkey"), rest // 2, 8.0) + hashed(F.col("l_partkey"), rest - rest // 2, 8.0)
    return cols


def line_points(spark: SparkSession, sf_dir: str, d: int = 64, dense: bool = True) -> DataFrame:
    """Long and wide: lineitem rows as ``d`` coordinates. Without dense ids no row moves."""
    base = _numbered_line(spark, sf_dir) if dense else _line(spark, sf_dir).withColumn("id", F.monotonically_increasing_id())
    return base.select("id", F.array(*line_vectors(d)).alias("x"), F.lit(1).cast("bigint").alias("w"))


def quantity_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three measures with the whole quantity as weight."""
    return _numbered_line(spark, sf_dir).select("id", F.array(*_measures()[1:]).alias("x"), F.col("l_quantity").cast("bigint").alias("w"))


def event_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events in time order: value, hour, day, type and number of the property."""
    df = table(spark, sf_dir, "events")
    hour = F.hour("ts")
    cols = [F.col("value"), F.sin(hour * 3.141592653589793 / 12), F.cos(hour * 3.141592653589793 / 12), F.dayofmonth("ts").cast("double")]
    cols += [F.when(F.col("event_type") == v, 5.0).otherwise(0.0) for v in ("click", "error", "purchase", "signup", "view")]
    cols += [F.coalesce(F.from_json("props", "k int")["k"].cast("double"), F.lit(0.0)) / 10, (F.pmod("user_id", F.lit(7))).cast("double"), (F.pmod("user_id", F.lit(11))).cast("double")]
    return df.select(F.col("event_id").alias("id"), F.array(*[c.cast("double") for c in cols]).alias("x"), F.lit(1).cast("bigint").alias("w"), "ts")


def tokens(df: DataFrame, key: str, text: str = "text") -> DataFrame:
    """``id, token, n``: lower-case ASCII tokens and their counts."""
    words = F.explode(F.split(F.lower(F.coalesce(text, F.lit(""))), TOKEN))
    return df.select(F.col(key).alias("id"), words.alias("token")).filter("token <> ''").groupBy("id", "token").agg(F.count("*").alias("n"))


def bag_of_words(df: DataFrame, key: str, buckets: int, text: str = "text") -> DataFrame:
    """Token counts hashed to ``buckets`` coordinates; rows without tokens are zero vectors and stay."""
    words = df.select(F.col(key).alias("id"), F.explode(F.split(F.lower(F.coalesce(text, F.lit(""))), TOKEN)).alias("token")).filter("token <> ''")
    counts = words.withColumn("b", F.pmod(F.conv(F.substring(F.md5("token"), 1, 7), 16, 10).cast("bigint"), F.lit(buckets)).cast("int")).groupBy("id", "b").agg(F.count("*").alias("n"))
    packed = counts.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("b", "n"))).alias("m"))
    rows = df.select(F.col(key).alias("id")).join(packed, "id", "left")
    x = F.transform(F.sequence(F.lit(0), F.lit(buckets - 1)), lambda i: F.coalesce(F.try_element_at(F.col("m"), i), F.lit(0)).cast("double"))
    return rows.select(F.col("id").cast("bigint").alias("id"), F.when(F.col("m").isNull(), F.array_repeat(F.lit(0.0), buckets)).otherwise(x).alias("x"), F.lit(1).cast("bigint").alias("w"))


def premerge(pts: DataFrame) -> DataFrame:
    """Equal points as one weighted point: a gain for discretized data, an exchange for nothing otherwise."""
    return pts.groupBy("x").agg(F.min("id").alias("id"), F.sum("w").alias("w")).select("id", "x", "w")


def replicated(pts: DataFrame) -> DataFrame:
    """Each point as many times as its weight says (for tests of weighted methods)."""
    return pts.select("id", "x", F.explode(F.sequence(F.lit(1), F.col("w").cast("int"))).alias("copy")).select("id", "x", F.lit(1).cast("bigint").alias("w"))


def multiplied(pts: DataFrame) -> DataFrame:
    """Coordinates times weight: what weights must not be mistaken for (for tests)."""
    return pts.select("id", F.transform("x", lambda v: v * F.col("w")).alias("x"), F.lit(1).cast("bigint").alias("w"))


def matrix(pts: DataFrame, most: int = 200_000):
    """A small table as a NumPy matrix ordered by id (bounded: tests and single-piece measures)."""
    import numpy as np

    rows = pts.select("id", "x").orderBy("id").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError("too many rows for one matrix")
    return np.array([list(r["x"]) for r in rows], dtype=float)


