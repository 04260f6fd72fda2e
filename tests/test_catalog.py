"""Registered queries against their SQL on the smallest tables."""

import duckdb
import pytest

from domsearch.plans.catalog import ORACLES, QUERIES
from domsearch.sources.tables import TABLES

NAMES = list(ORACLES)


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for name in TABLES:
        c.sql(f"create view {name} as select * from '{sf}/{name}.parquet'")
    return c


def _rows(rows):
    return sorted(tuple(repr(v + 0.0) if isinstance(v, float) else str(v) for v in r) for r in rows)


@pytest.mark.parametrize("name", NAMES)
def test_oracle(spark, sf, duck, name):
    df, want = QUERIES[name](spark, sf), duck.sql(ORACLES[name])
    columns = sorted(df.columns)
    assert columns == sorted(want.columns)
    assert _rows(df.select(*columns).collect()) == _rows(want.select(*(f'"{c}"' for c in columns)).fetchall())


def test_every_oracle_has_its_query():
    assert set(ORACLES) <= set(QUERIES)
