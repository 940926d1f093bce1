"""Queries against their SQL in DuckDB on the smallest tables, and the driver contract."""

import os
import subprocess
import sys

import duckdb
import pandas as pd
import pytest

from sparse_neighbors import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = ("knn_exhaustive", "knn_pruned_keep", "knn_pruned_natural", "knn_pruned_rare", "methods_agree", "theorem", "w4_result", "knn_pruned_default", "knn_pruned_doc", "knn_pruned_order", "knn_pruned_supplier")
QUICK = [n for n in catalog.ORACLES if not n.startswith(SLOW)]


@pytest.fixture(scope="module")
def duck(data):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from read_parquet('{data}/{t}.parquet')")
    return con


def canonical(df):
    df = df[sorted(df.columns)]
    cells = [tuple("NULL" if pd.isna(v) else f"{v:.9g}" if isinstance(v, float) else str(v) for v in row) for row in df.itertuples(index=False)]
    return list(df.columns), sorted(cells)


@pytest.mark.parametrize("name", QUICK)
def test_query_matches_sql(spark, data, duck, name):
    got = catalog.QUERIES[name](spark, data).toPandas()
    want = duck.execute(catalog.ORACLES[name]).df()
    assert canonical(got) == canonical(want)


@pytest.mark.parametrize("name", sorted(set(catalog.QUERIES) - set(catalog.ORACLES)))
def test_query_without_sql_runs(spark, data, name):
    got = catalog.QUERIES[name](spark, data)
    assert got.count() > 0
    if name == "rel_agg_approx":
        assert all(got.first())


def test_entry_imports_without_a_session():
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    code = "import __spark_entry__ as e; assert set(e.oracle_sql()) <= set(e.queries())"
    subprocess.run([sys.executable, "-c", code], cwd=root, check=True, timeout=120)


def test_entry_runs(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
