"""Registered queries against their SQL in DuckDB, on the smallest tables."""

import re

import duckdb
import pytest

import __spark_entry__ as entry
from runcheck import TABLES, rows_of

SF = "/root/testdata/sf0.001"
#: Long replays whose code the other reservoir queries and test_streams run too, and a build of many cells.
LONG = {"reservoir_day_k100", "reservoir_week_k1000", "reservoir_lineitem_year", "os_store_rows_read"}
SAMPLING = sorted(n for n in entry.queries() if not re.match(r"op\d|pipeline", n) and n not in LONG)
NAMES = [n for n in SAMPLING if n in entry.oracle_sql()]
REST = [n for n in SAMPLING if n not in entry.oracle_sql()]


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, db, name):
    df, rel = entry.queries()[name](spark, SF), db.sql(entry.oracle_sql()[name])
    assert rows_of(df.columns, df.collect()) == rows_of(rel.columns, rel.fetchall())


@pytest.mark.parametrize("name", REST)
def test_query_without_sql_runs(spark, name):
    assert entry.queries()[name](spark, SF).count() >= 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_oracle_names_are_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())
