"""Replays, restarts and late data."""

import glob
import os

from pyspark.sql import functions as F

from kmfold.sources import points
from kmfold.staging import scratch_path
from kmfold.streaming import log, windows


def test_log_survives_a_restart(spark, sf):
    pts = points.event_points(spark, sf).select("id", "x", "w")
    path = windows.split_files(pts.filter("id < 500"), 2, "id")
    out, check = scratch_path(spark, "log"), scratch_path(spark, "check")
    schema = "id bigint, x array<double>, w bigint"
    log.summarize_stream(windows.file_stream(spark, path, schema), out, check, 3, 100, 60).awaitTermination()
    assert log.compact(spark, out, 60).agg(F.sum("w")).first()[0] == 500
    pts.filter("id >= 500").coalesce(1).write.mode("append").parquet(path)
    log.summarize_stream(windows.file_stream(spark, path, schema), out, check, 3, 100, 60).awaitTermination()
    s = log.compact(spark, out, 60)
    assert s.agg(F.sum("w")).first()[0] == 1000 and s.count() <= 60


def test_late_rows_are_dropped_and_counted(spark, sf):
    e = points.table(spark, sf, "events")
    path = scratch_path(spark, "late")
    old, new = e.filter("event_id < 100"), e.filter("event_id >= 100")
    new.coalesce(1).write.mode("append").parquet(path)
    q = windows.tumbling(windows.file_stream(spark, path, windows.EVENTS)).writeStream.format("memory").queryName("late_windows").outputMode("update").option("checkpointLocation", scratch_path(spark, "c")).start()
    q.processAllAvailable()
    old.coalesce(1).write.mode("append").parquet(path)
    q.processAllAvailable()
    dropped = sum(op["numRowsDroppedByWatermark"] for p in q.recentProgress for op in p["stateOperators"])
    q.stop()
    assert dropped > 0
    assert spark.table("late_windows").agg(F.sum("n")).first()[0] == new.count()


def test_files_are_written_in_their_order(spark):
    """The first range takes longest to write, and is still the first that a stream reads."""
    text = F.when(F.col("id") < 20_000, F.array_join(F.transform(F.sequence(F.lit(1), F.lit(60)), lambda i: F.sha2(F.concat_ws("-", i, "id"), 512)), "")).otherwise("")
    path = windows.split_files(spark.range(60_000).withColumn("text", text), 3, "id")
    files = sorted(glob.glob(f"{path}/*.parquet"), key=os.path.getmtime)
    lows = [spark.read.parquet(f).agg(F.min("id")).first()[0] for f in files]
    assert len(lows) == 3 and lows == sorted(lows)
