"""Every registered query with SQL against DuckDB on the smallest scale, a few at a time."""

import glob
import math
import os

import duckdb
import pytest

import __spark_entry__ as entry_module
from treeloom.workloads.registry import ORACLES, QUERIES

NAMES = sorted(ORACLES)


def rows_of(frame) -> list[str]:
    frame = frame[sorted(frame.columns)]

    def plain(v):
        if v is None or (isinstance(v, float) and math.isnan(v)):
            return None
        return float(v) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)

    return sorted(repr([plain(v) for v in row]) for row in frame.astype(object).values.tolist())


@pytest.fixture(scope="module")
def duck(small):
    c = duckdb.connect()
    for f in glob.glob(f"{small}/*.parquet"):
        c.sql(f"create view {os.path.basename(f)[:-8]} as select * from read_parquet('{f}')")
    return c


@pytest.mark.parametrize("name", NAMES)
def test_against_sql(spark, small, duck, name):
    got, want = QUERIES[name](spark, small).toPandas(), duck.sql(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows_of(got) == rows_of(want)


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES)))
def test_runs(spark, small, name):
    assert QUERIES[name](spark, small).count() >= 0


def test_entry(spark):
    assert entry_module.entry(spark).count() > 0
    assert set(ORACLES) <= set(entry_module.queries())
