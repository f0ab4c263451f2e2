"""Every query of the engine against its DuckDB SQL on the smallest tables."""

import glob
import math
import os

import duckdb
import pytest

from kmfold.plans import catalog

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM read_parquet('{f}')")
    return con


def normal(rows, names):
    order = sorted(range(len(names)), key=names.__getitem__)

    def cell(v):
        if isinstance(v, bool):
            return str(v)
        if isinstance(v, (int, float)) or type(v).__name__ == "Decimal":
            v = float(v)
            return "nan" if math.isnan(v) else f"{v:.9g}"
        return str(v)

    return sorted(tuple(cell(r[i]) for i in order) for r in rows)


def test_every_query_has_sql():
    assert set(catalog.QUERIES) == set(catalog.ORACLE_SQL)


@pytest.mark.parametrize("name", sorted(catalog.QUERIES))
def test_query_equals_sql(spark, duck, name):
    df = catalog.QUERIES[name](spark, SF)
    got = [tuple(r) for r in df.collect()]
    cur = duck.execute(catalog.ORACLE_SQL[name])
    names = [c[0] for c in cur.description]
    assert sorted(names) == sorted(df.columns)
    assert normal(got, df.columns) == normal(cur.fetchall(), names)


def test_flagship(spark):
    rows = catalog.flagship(spark, SF).collect()
    assert len(rows) == 5 and sum(r["weight"] for r in rows) == 500
    assert abs(sum(r["cost_share"] for r in rows) - 1) < 1e-9
