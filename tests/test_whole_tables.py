"""Queries look at every row of a table larger than the smallest ones."""

import glob
import os

import duckdb
import pytest

from kmfold.plans import catalog
from kmfold.sources import points
from test_catalog import normal

LARGE = "/root/testdata/sf0.1"
SMALL = "/root/testdata/sf0.001"
FROM_TABLES = ["block_signal_onecenter", "cost_cube", "generator_data_source", "memory_guard", "method_advice", "one_center_expectations", "nested_simplex_optimum"]


@pytest.mark.parametrize("name", ["svd_random_vs_exact", "weighted_subspace", "naive_against_exact"])
def test_no_row_is_left_out(spark, monkeypatch, name):
    from kmfold.operators import linalg, sphere

    seen = []
    compare, exact, offer = linalg.svd_comparison, linalg.svd_exact, sphere.SphereTree.offer
    monkeypatch.setattr(linalg, "svd_comparison", lambda a, *r: seen.append(len(a)) or compare(a, *r))
    monkeypatch.setattr(linalg, "svd_exact", lambda a, *r: seen.append(len(a)) or exact(a, *r))
    monkeypatch.setattr(sphere.SphereTree, "offer", lambda self, x, *r: seen.append(len(x)) or offer(self, x, *r))
    rows = catalog.QUERIES[name](spark, LARGE).collect()
    assert min(seen) == points.emb64(spark, LARGE).count() == 2000
    assert all(v for r in rows for v in r.asDict().values() if isinstance(v, bool))


def test_blocks_hold_the_whole_table(spark):
    from kmfold.plans.method_queries import matrices

    got = [m.shape for m in matrices(points.emb64(spark, LARGE), 600)]
    assert len(got) == 4 and sum(n for n, _ in got) == 2000


def test_trees_are_reduced_to_one_root(spark, monkeypatch):
    from kmfold.operators import summaries

    rows = catalog.QUERIES["node_counters"](spark, LARGE).collect()
    assert {r["level"]: r["counted"] for r in rows} == {0: True, 1: True, 2: True, 3: True}
    planned, plan = [], summaries.plan_levels
    monkeypatch.setattr(summaries, "plan_levels", lambda n, params: planned.append(n) or plan(n, params))
    catalog.QUERIES["repeated_runs"](spark, LARGE).collect()
    assert set(planned) == {2000}


@pytest.mark.parametrize("name", FROM_TABLES)
def test_result_is_that_of_the_given_table(spark, name):
    """Another table, another result, and the one of the SQL."""
    got = {sf: catalog.QUERIES[name](spark, sf) for sf in (SMALL, LARGE)}
    rows = {sf: normal([tuple(r) for r in df.collect()], df.columns) for sf, df in got.items()}
    assert rows[SMALL] != rows[LARGE]
    con = duckdb.connect()
    for f in glob.glob(f"{LARGE}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM read_parquet('{f}')")
    cur = con.execute(catalog.ORACLE_SQL[name])
    assert rows[LARGE] == normal(cur.fetchall(), [c[0] for c in cur.description])
