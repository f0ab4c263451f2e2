"""Live summaries in keyed state: one summarizer a shard, kept between micro-batches."""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kmfold.staging import ship_package

OUT = "shard bigint, n bigint, features bigint, ss_total double"


def live_summary(points: DataFrame, shards: int, m: int) -> DataFrame:
    """Per shard and micro-batch: points taken in so far, features held, and the energy they stand for.

    State is the summarizer's arrays (bounded by ``m``); a restart from the checkpoint
    goes on with them.
    """
    ship_package(points.sparkSession)

    def update(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        from kmfold.operators.sphere import SphereTree

        tree = SphereTree.restore(pickle.loads(state.get[0])) if state.exists else None
        for pdf in frames:
            if not len(pdf):
                continue
            pdf = pdf.sort_values("id")
            x = np.stack(pdf["x"].to_numpy())
            tree = tree or SphereTree(m, x.shape[1], int(key[0]))
            tree.offer(x, pdf["w"].to_numpy())
        state.update((pickle.dumps(tree.snapshot()),))
        mean, w, within = tree.rows()
        yield pd.DataFrame({"shard": [int(key[0])], "n": [int(w.sum())], "features": [len(w)], "ss_total": [float((w * (mean * mean).sum(1)).sum() + within.sum())]})

    keyed = points.withColumn("shard", F.pmod(F.col("id"), F.lit(shards)))
    return keyed.select("shard", "id", "x", "w").groupBy("shard").applyInPandasWithState(update, OUT, "tree binary", "update", "NoTimeout")
