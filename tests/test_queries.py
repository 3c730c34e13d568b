"""Every registered query with an oracle against DuckDB on the same tables."""

import glob
import os

import duckdb
import pytest

from spanweave.oracle import MEASURED, SQL
from spanweave.queries import QUERIES

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def tables():
    con = duckdb.connect()
    for path in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM read_parquet('{path}')")
    return con


def test_all_have_oracles():
    assert set(SQL) | set(MEASURED) == set(QUERIES) and not set(SQL) & set(MEASURED)


@pytest.mark.parametrize("name", sorted(SQL))
def test_query(spark, tables, name):
    want = tables.execute(SQL[name]).fetchdf()
    got = QUERIES[name](spark, SF).toPandas()
    columns = sorted(want.columns)
    assert sorted(got.columns) == columns
    assert sorted(map(tuple, got[columns].astype(str).values)) == sorted(map(tuple, want[columns].astype(str).values))
