"""Every registered query with SQL against DuckDB on the smallest tables."""

import datetime
import decimal
import os

import duckdb
import numpy as np
import pytest

import __spark_entry__ as contract
from densesql.sources.tables import TABLES

QUERIES, ORACLES = contract.queries(), contract.oracle_sql()


def plain(v):
    if v is None or isinstance(v, float | np.floating) and v != v:
        return None
    if isinstance(v, float | np.floating | decimal.Decimal):
        return f"{round(float(v), 6) + 0.0:.6f}"
    if isinstance(v, bool | np.bool_):
        return bool(v)
    if isinstance(v, int | np.integer):
        return int(v)
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None).isoformat()
    return [plain(x) for x in v] if isinstance(v, list) else str(v)


@pytest.fixture(scope="module")
def duck(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        con.execute(f"create view {t} as select * from '{path}{'/*.parquet' if os.path.isdir(path) else ''}'")
    return con


def test_names_match():
    assert set(ORACLES) <= set(QUERIES) and len(QUERIES) > 200


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_matches_its_sql(spark, sf_dir, duck, name):
    df = QUERIES[name](spark, sf_dir)
    found = duck.execute(ORACLES[name])
    columns = [d[0] for d in found.description]
    assert sorted(columns) == sorted(df.columns)
    at = [columns.index(c) for c in df.columns]
    want = sorted(([plain(r[i]) for i in at] for r in found.fetchall()), key=repr)
    assert sorted(([plain(x) for x in r] for r in df.collect()), key=repr) == want
