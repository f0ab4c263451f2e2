"""Event-time windows, deduplication, joins and late data over the event stream."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kmfold.staging import scratch_path, stage

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def replay(spark: SparkSession, sf_dir: str, table: str = "events", schema: str = EVENTS) -> DataFrame:
    """A table as a file stream, with an explicit schema."""
    return spark.readStream.schema(schema).option("pathGlobFilter", f"{table}.parquet").parquet(sf_dir)


def file_stream(spark: SparkSession, path: str, schema: str, files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def rate_points(spark: SparkSession, rows: int, d: int, seed: int = 3) -> DataFrame:
    """Points ``id, x, w`` from a rate stream, ``rows`` a micro-batch; coordinates by hash of their place."""
    from kmfold.functions.hashing import uniform

    rate = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows).option("numPartitions", 2).load()
    x = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: uniform(F.col("value") * d + j, seed))
    return rate.select(F.col("value").alias("id"), x.alias("x"), F.lit(1).cast("bigint").alias("w"))


def files_in_turn(frames: list[DataFrame]) -> str:
    """Write each table as one file, one after the other: micro-batches in any order of time."""
    path = scratch_path(frames[0].sparkSession, "stream_input")
    for df in frames:
        df.coalesce(1).write.mode("append").parquet(path)
    return path


def split_files(df: DataFrame, files: int, order: str) -> str:
    """Write a bounded table as files in the order of a column: a stream of several micro-batches.

    A stream takes files by the time they were written, so a later range is written after an earlier one.
    """
    dealt = stage(df.repartitionByRange(files, order).withColumn("_file", F.spark_partition_id()), "dealt", ["_file"])
    return files_in_turn([dealt.filter(F.col("_file") == i).drop("_file").coalesce(1).sortWithinPartitions(order) for i in range(files)])


def run_to_table(out: DataFrame, mode: str, name: str = "stream_output") -> DataFrame:
    """Run a stream once over what is there and return its output as a table."""
    spark = out.sparkSession
    path, checkpoint = scratch_path(spark, name), scratch_path(spark, "stream_checkpoint")
    if mode == "append":
        q = out.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(out.schema).parquet(path)

    def write(df: DataFrame, batch_id: int) -> None:
        df.withColumn("_batch", F.lit(batch_id).cast("bigint")).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    q = out.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(out.withColumn("_batch", F.lit(0).cast("bigint")).schema).option("recursiveFileLookup", "true").parquet(path)


def timed(events: DataFrame, delay: str = "2 hours") -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return timed(events).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("bigint")).alias("cents"))


def sliding(events: DataFrame, width: str = "2 days", slide: str = "1 day") -> DataFrame:
    return timed(events).groupBy(F.window("ts", width, slide).alias("w")).agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return timed(events).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))


def first_of_each(events: DataFrame, keys: list[str]) -> DataFrame:
    """Rows of a repeated key are dropped while the watermark lasts."""
    return timed(events).dropDuplicatesWithinWatermark(keys)


def against_table(events: DataFrame, table: DataFrame, on: str) -> DataFrame:
    """Stream and static table: the table's side is chosen by size at planning."""
    return events.join(table, on)


def within(left: DataFrame, right: DataFrame, key: str, interval: str) -> DataFrame:
    """Stream and stream: equal keys, right at most ``interval`` after left."""
    a, b = timed(left).alias("a"), timed(right).alias("b")
    return a.join(b, F.expr(f"a.{key} = b.{key} AND b.ts > a.ts AND b.ts <= a.ts + interval {interval}"))
