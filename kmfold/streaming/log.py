"""One pass over a stream: a log of summaries, one a micro-batch.

Each micro-batch is summarized by the leaf kernel and written below its batch id, so
a replayed batch overwrites itself. ``compact`` reads all leaves and reduces them along
a tree; it writes nothing, so the log stays the only state.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kmfold.operators.summaries import SUMMARY, SUMMARY_COLUMNS, piecewise_full, reduce_levels

BATCH = f"{SUMMARY}, batch bigint"


def summary_writer(path: str, k: int, ps: int, l: int | None, m: int, seed: int = 0) -> Callable[[DataFrame, int], None]:  # noqa: E741
    """A ``foreachBatch`` function that writes one reduced summary a batch."""

    def write(df: DataFrame, batch_id: int) -> None:
        s = piecewise_full(df, k, ps, l, m, "random" if l else "none", "sharded", seed + batch_id)
        s.select(*SUMMARY_COLUMNS).withColumn("node", F.lit(batch_id).cast("bigint")).write.mode("overwrite").parquet(f"{path}/level=0/batch={batch_id}")

    return write


def summarize_stream(points: DataFrame, path: str, checkpoint: str, k: int, ps: int, m: int, l: int | None = None, available_now: bool = True):  # noqa: E741
    """Run the log over a streaming points table (id, x, w)."""
    writer = points.writeStream.foreachBatch(summary_writer(path, k, ps, l, m)).option("checkpointLocation", checkpoint)
    return writer.trigger(availableNow=True).start() if available_now else writer.start()


def read_log(spark: SparkSession, path: str) -> DataFrame:
    """All leaf summaries of the log."""
    return spark.read.schema(BATCH).option("basePath", f"{path}/level=0").parquet(f"{path}/level=0").select(*SUMMARY_COLUMNS)


def compact(spark: SparkSession, path: str, m: int, fan: int = 8, seed: int = 0) -> DataFrame:
    """The whole stream's summary so far: leaves reduced by a tree of degree ``fan``."""
    return reduce_levels(read_log(spark, path), m, fan=fan, seed=seed).select(*SUMMARY_COLUMNS)
