"""Intermediate tables in the folder that all executors share.

``stage`` cuts lineage by writing a Parquet table below ``spark.checkpoint.dir``
and reading it back, so a lost executor never costs more than the current step.
The setting is read from the session; only where it is unset (tests, a single
machine) is a folder of our own used.
"""

from __future__ import annotations

import atexit
import io
import os
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Only for a master that runs in one process.
FALLBACK_ROOT = "/tmp/checkpoints/kmfold"
#: More partitions of one exchange than this cost more than they spread.
MOST_PARTITIONS = 1 << 17
#: Estimates from here on mean that the plan does not know.
UNKNOWN_BYTES = 1 << 58
_made: dict[str, SparkSession] = {}
_shipped: set[str] = set()


def scratch_root(spark: SparkSession) -> str:
    """The shared folder for intermediate tables of this session; a cluster has to name one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        named = found.get() if found.isDefined() else None
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        named = FALLBACK_ROOT
    return named.rstrip("/")


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder, removed when the driver ends."""
    path = f"{scratch_root(spark)}/kmfold-{uuid.uuid4().hex}/{name}"
    _made[path] = spark
    return path


def stage(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and return the table read back."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    writer = df.write
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    back = spark.read.schema(df.schema).parquet(path).select(*df.columns)
    back._kmfold_path = path
    return back


def discard(df: DataFrame) -> None:
    """Delete a staged table that no later step reads."""
    path = getattr(df, "_kmfold_path", None)
    if path in _made:
        _delete(_made.pop(path), path)


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path).getParent()
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


@atexit.register
def _clean() -> None:
    for path, spark in list(_made.items()):
        try:
            if spark.sparkContext._jsc is not None:
                _delete(spark, path)
        except Exception:  # the JVM is already gone: nothing can be deleted any more
            return


def input_bytes(df: DataFrame) -> int:
    """The optimizer's size estimate of ``df``: file sizes, no job is run.

    Where the plan gives none (rows from the driver, an RDD), the texts are measured.
    """
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    if size < UNKNOWN_BYTES:
        return size
    texts = [F.coalesce(F.sum(F.octet_length(c)), F.lit(0)) for c, kind in df.dtypes if kind in ("string", "binary")]
    row = df.agg(F.count("*") * 16, *texts).first()
    return int(sum(row))


def pieces_for(df: DataFrame, bytes_each: int, least: int = 1, most: int = 1 << 30) -> int:
    """How many pieces of about ``bytes_each`` the input makes (``most``: for partitions or plan literals, not for memory)."""
    size = input_bytes(df)
    return max(least, min(most, -(-size // bytes_each)))


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def ship_package(spark: SparkSession) -> None:
    """Give the executors this package, once for each application."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    here = Path(__file__).resolve().parent
    buffer = io.BytesIO()
    with zipfile.ZipFile(buffer, "w") as z:
        for p in sorted(here.rglob("*.py")):
            z.write(p, f"{here.name}/{p.relative_to(here)}")
    folder = f"{os.environ.get('TMPDIR', '/tmp')}"
    target = Path(folder) / f"kmfold-{uuid.uuid4().hex}"
    target.mkdir(parents=True, exist_ok=True)
    path = target / "kmfold_src.zip"
    path.write_bytes(buffer.getvalue())
    spark.sparkContext.addPyFile(str(path.resolve()))
    _shipped.add(app)
