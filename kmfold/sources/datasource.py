"""Generated points as a Spark data source with a partitioned reader.

``spark.read.format("kmfold_cube").options(n=…, d=…, half=…, seed=…, partitions=…)``:
``id, x, w`` uniform in a cube. Rows depend on their id alone, not on the partitioning.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from kmfold.functions.arrays import to_column
from kmfold.functions.hashing import FACTORS, PRIME
from kmfold.staging import ship_package

BLOCK = 4096


def hash_block(key: np.ndarray, seed: int) -> np.ndarray:
    """The engine's arithmetic hash on an array of keys."""
    h = key.astype(np.int64) + 1
    for c in FACTORS:
        h = (h * h + c * h + seed) % PRIME
    return h


class Rows(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class CubeReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.d = int(options.get("n", 1000)), int(options.get("d", 8))
        self.half, self.seed = float(options.get("half", 10.0)), int(options.get("seed", 3))
        self.parts = int(options.get("partitions", 4))

    def partitions(self):
        cuts = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [Rows(a, b) for a, b in zip(cuts, cuts[1:]) if b > a]

    def read(self, partition):
        for a in range(partition.start, partition.stop, BLOCK):
            ids = np.arange(a, min(a + BLOCK, partition.stop))
            u = hash_block(ids[:, None] * self.d + np.arange(self.d), self.seed) / float(PRIME)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), to_column((u * 2.0 - 1.0) * self.half), pa.array(np.ones(len(ids), np.int64))], ["id", "x", "w"])


class CubeSource(DataSource):
    @classmethod
    def name(cls):
        return "kmfold_cube"

    def schema(self):
        return "id bigint, x array<double>, w bigint"

    def reader(self, schema):
        return CubeReader(self.options)


def register(spark: SparkSession) -> None:
    ship_package(spark)
    spark.dataSource.register(CubeSource)
