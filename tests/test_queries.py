"""Every registered query of the engine against its SQL, on the smallest tables."""

import math
import os

import duckdb
import pytest

from epsgraph import registry
from tests.conftest import TINY


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for name in os.listdir(TINY):
        if name.endswith(".parquet"):
            c.execute(f"create view {name[:-8]} as select * from '{TINY}/{name}'")
    return c


def plain(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return "null"
    return f"{v:.9g}" if isinstance(v, float) else str(v)


def table(columns, rows):
    return sorted(tuple(map(plain, r)) for r in rows)


@pytest.mark.parametrize("name", registry.ALL)
def test_query(spark, duck, name):
    query, sql = registry.ALL[name]
    df = query(spark, TINY)
    columns = sorted(df.columns)
    got = table(columns, df.select(*columns).collect())
    if sql:
        assert got == table(columns, duck.execute(f"SELECT {', '.join(columns)} FROM ({sql})").fetchall())


def test_flagship(spark):
    assert registry.flagship(spark, TINY).first().n == 500
