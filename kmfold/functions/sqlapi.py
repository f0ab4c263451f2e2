"""Vectorized functions for SQL and DataFrames: assignment UDF, feature UDAF, projection and summary UDTFs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udtf, pandas_udf

from kmfold.functions.arrays import block_distances, to_column, to_matrix
from kmfold.staging import ship_package


def assign_udf(centers: list[tuple[int, list[float]]]):
    """Nearest center of each vector: a struct of d2 and cid."""
    cids = np.array([cid for cid, _ in centers], np.int32)
    c = np.array([v for _, v in centers], np.float64)

    @pandas_udf("d2 double, cid int")
    def near(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for s in batches:
            x = np.stack(s.to_numpy()) if len(s) else np.zeros((0, c.shape[1]))
            d2 = block_distances(x, c)
            k = d2.argmin(axis=1)
            # the chosen distance anew, free of cancellation
            diff = x - c[k]
            yield pd.DataFrame({"d2": np.einsum("ij,ij->i", diff, diff), "cid": cids[k]})

    return near


def panel_udf(panel: list[list]):
    """Squared distance to the nearest center of each set of a panel."""
    sets = [np.array([v for _, v in p], np.float64) for p in panel]

    @pandas_udf("array<double>")
    def near(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            x = np.stack(s.to_numpy()) if len(s) else np.zeros((0, sets[0].shape[1]))
            cols = []
            for c in sets:
                k = block_distances(x, c).argmin(axis=1)
                diff = x - c[k]
                cols.append(np.einsum("ij,ij->i", diff, diff))
            yield pd.Series(list(np.stack(cols, axis=1)))

    return near


def cf_rows_udf():
    """Feature of each weighted point, block by block."""

    @pandas_udf("w bigint, ls array<double>, ss double")
    def cf_rows(x: pd.Series, w: pd.Series) -> pd.DataFrame:
        m = np.stack(x.to_numpy())
        weight = w.to_numpy().astype(float)
        return pd.DataFrame({"w": w.astype("int64"), "ls": list(m * weight[:, None]), "ss": weight * (m * m).sum(1)})

    return cf_rows


def cost_udaf():
    """Grouped aggregate: cost of a group against its own centroid (cross-check of the built-in way)."""

    @pandas_udf("double")
    def set_cost(x: pd.Series, w: pd.Series) -> float:
        m = np.stack(x.to_numpy()).astype(float)
        weight = w.to_numpy().astype(float)
        mean = (weight[:, None] * m).sum(0) / weight.sum()
        return float((weight * ((m - mean) ** 2).sum(1)).sum())

    return set_cost


class RankProjection:
    """``rank_l_projection(l, TABLE(..) PARTITION BY piece ORDER BY id)`` over columns id, x, w."""

    def __init__(self):
        self.l, self.batches = 1, []

    def eval(self, l: pa.Array, table: pa.RecordBatch):  # noqa: E741
        self.l = int(l[0].as_py())
        self.batches.append(table)
        return iter(())

    def terminate(self):
        from kmfold.operators.linalg import project_matrix

        if self.batches:
            t = pa.Table.from_batches(self.batches)
            out, _ = project_matrix(to_matrix(t.column("x")), self.l, w=t.column("w").to_numpy(), kind="exact")
            yield pa.table({"id": t.column("id").cast(pa.int64()), "x": to_column(out), "w": t.column("w").cast(pa.int64())})


class SphereSummary:
    """``sphere_summary(m, TABLE(..))`` over columns id, x, w: one summary for each partition of the call."""

    def __init__(self):
        self.tree, self.m = None, 1

    def eval(self, m: pa.Array, table: pa.RecordBatch):
        from kmfold.operators.sphere import SphereTree

        x = to_matrix(table.column("x"))
        if self.tree is None and len(x):
            self.tree = SphereTree(int(m[0].as_py()), x.shape[1])
        if len(x):
            self.tree.offer(x, table.column("w").to_numpy().astype(np.int64))
        return iter(())

    def terminate(self):
        if self.tree is not None:
            mean, w, within = self.tree.rows()
            yield pa.table({"id": pa.array(np.arange(len(w)), pa.int64()), "x": to_column(mean), "w": pa.array(w, pa.int64()), "ss_within": pa.array(within)})


def register(spark: SparkSession) -> None:
    """Make the functions callable from SQL text."""
    ship_package(spark)
    spark.udtf.register("rank_l_projection", arrow_udtf(RankProjection, returnType="id bigint, x array<double>, w bigint"))
    spark.udtf.register("sphere_summary", arrow_udtf(SphereSummary, returnType="id bigint, x array<double>, w bigint, ss_within double"))
    spark.udf.register("set_cost", cost_udaf())
    spark.udf.register("cf_row", cf_rows_udf())
