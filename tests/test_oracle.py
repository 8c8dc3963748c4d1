"""Every key whose SQL is cheap against DuckDB on the same tables."""

import os
from datetime import datetime
from decimal import Decimal

import duckdb
import pytest

from passagekit.plans import registry

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for f in os.listdir(SF):
        c.sql(f"create view {f.removesuffix('.parquet')} as select * from '{SF}/{f}'")
    return c


def plain(v):
    """Numbers as floats, times as text (compared exactly)."""
    return float(v) if isinstance(v, (float, Decimal)) else v.isoformat() if isinstance(v, datetime) else v


def rows(cols, found):
    by = sorted(range(len(cols)), key=lambda i: cols[i])
    return sorted((tuple(plain(r[i]) for i in by) for r in found), key=str)


@pytest.mark.parametrize("name", [n for n, (_, sql) in registry.ALL.items() if sql and not n.startswith("boot_auc")])
def test_same_rows(spark, con, name):
    f, sql = registry.ALL[name]
    df, want = f(spark, SF), con.sql(sql)
    assert sorted(df.columns) == sorted(want.columns)
    a, b = rows(df.columns, df.collect()), rows(want.columns, want.fetchall())
    assert len(a) == len(b)
    for x, y in zip(a, b, strict=True):
        assert x == pytest.approx(y, abs=1e-9)
