"""Every query with an SQL twin gives the same rows as the SQL, on the smallest tables."""

import glob
import os

import duckdb
import pytest

from tests.conftest import SMALL
from vecquant.plans import catalog


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for f in glob.glob(f"{SMALL}/*.parquet"):
        c.sql(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return c


def plain(v):
    return repr(v + 0.0) if isinstance(v, float) else v.isoformat() if hasattr(v, "isoformat") else repr(v)


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_query_equals_sql(spark, duck, name):
    df = catalog.QUERIES[name](spark, SMALL)
    columns = sorted(df.columns)
    own = sorted(tuple(plain(r[c]) for c in columns) for r in df.collect())
    result = duck.sql(catalog.ORACLES[name])
    assert sorted(result.columns) == columns
    place = [result.columns.index(c) for c in columns]
    assert own == sorted(tuple(plain(r[i]) for i in place) for r in result.fetchall())


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 1000
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


MOVED = ["aligned_bytes", "base_change", "block_layout", "fp32_gib", "index_bytes_model", "inverted_layout", "kuma_grid", "kuma_kernel_explog", "kuma_kernel_poly", "kuma_kernel_pow", "kuma_pdf_grid", "kuma_quantile_grid"]


@pytest.mark.parametrize("name", MOVED)
def test_query_reads_the_given_vectors(spark, name):
    plan = catalog.QUERIES[name](spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert "FileScan parquet" in plan and "embedding:array<float>" in plan
