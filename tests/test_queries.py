"""Every registered query with SQL gives the rows that DuckDB gives, on the smallest tables."""

from __future__ import annotations

import math

import duckdb
import pytest

import __spark_entry__ as entry
from tileaqp.operators.checked import WORKLOADS
from tileaqp.operators.library import QUERIES, SQL

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    c.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def plain(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return "null"
    return f"{v:.8g}" if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", sorted(SQL))
def test_same_rows_as_sql(spark, sf, duck, name):
    run, sql = QUERIES[name], SQL[name]
    if workload := WORKLOADS.get(name.removesuffix("_checked")):  # the first queries; the whole paths take minutes
        workload = workload.shorter(3)
        run, sql = workload.run, workload.sql()
    got, want = run(spark, sf), duck.sql(sql)
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    rows = sorted(tuple(plain(r[c]) for c in columns) for r in got.collect())
    where = [want.columns.index(c) for c in columns]
    assert rows == sorted(tuple(plain(r[i]) for i in where) for r in want.fetchall())


def test_entry_and_names(spark):
    assert set(entry.oracle_sql()) <= set(entry.queries())
    df = entry.entry(spark)
    assert df.count() == 10 and "rel_err" in df.columns
