"""Queries against DuckDB on the smallest tables."""

import decimal

import duckdb
import pytest

import __spark_entry__ as entry
from spreadsample.functions.points import TABLES

SF = "/root/testdata/sf0.001"
#: The claims of the experiments (w1 to w14) are about tables larger than these.
CLAIMS = {f"w{i}" for i in range(1, 15)}
NAMES = sorted(k for k in entry.oracle_sql() if not (k.startswith("op") and k[2].isdigit()) and k != "pipeline" and k.split("_")[0] not in CLAIMS)


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    return c


def tidy(x):
    return round(x, 7) if isinstance(x, float) else float(x) if isinstance(x, decimal.Decimal) else x


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_duckdb(spark, duck, name):
    ours = entry.queries()[name](spark, SF)
    result = duck.execute(entry.oracle_sql()[name])
    cols = [d[0] for d in result.description]
    assert sorted(cols) == sorted(ours.columns)
    want = sorted((tuple(tidy(v) for v in r) for r in result.fetchall()), key=repr)
    assert sorted((tuple(tidy(r[c]) for c in cols) for r in ours.collect()), key=repr) == want


def test_entry(spark):
    rows = entry.entry(spark)
    assert rows.columns == ["id", "x", "y", "burden", "density"] and rows.count() == 100
