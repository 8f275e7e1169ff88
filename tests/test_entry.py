"""The driver contract, and the queries against their SQL on the smallest tables."""

import datetime
from pathlib import Path

import duckdb
import pytest

import __spark_entry__ as driver


def test_flagship(spark):
    assert driver.entry(spark).count() > 0


def test_names():
    assert set(driver.oracle_sql()) <= set(driver.queries())


def _plain(v):
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None).isoformat()
    return round(v, 5) + 0.0 if isinstance(v, float) else v


@pytest.fixture(scope="module")
def con(small):
    c = duckdb.connect()
    for f in Path(small).glob("*.parquet"):
        c.sql(f"create view {f.stem} as select * from '{f}'")
    return c


@pytest.mark.parametrize("name", sorted(driver.oracle_sql()))
def test_query_equals_sql(spark, small, con, name):
    got = driver.queries()[name](spark, small)
    want = con.sql(driver.oracle_sql()[name])
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    key = lambda row: tuple((v is None, str(v)) for v in row)
    a = sorted((tuple(_plain(r[c]) for c in columns) for r in got.collect()), key=key)
    b = sorted((tuple(_plain(r[want.columns.index(c)]) for c in columns) for r in want.fetchall()), key=key)
    assert a == b


@pytest.mark.parametrize("name", ["generate_md5", "precision_recall", "eleven_point"])
def test_query_reads_given_tables(spark, small, name):
    assert any(f.startswith(f"file://{small}") or f.startswith(f"file:{small}") for f in driver.queries()[name](spark, small).inputFiles())
