"""Every query that SQL can express equals its SQL on the smallest tables; the others run."""

import os

import duckdb
import pytest
from attrition import catalogue
from attrition.sources.tables import SCHEMAS

QUERIES, ORACLES = catalogue.queries(), catalogue.oracle_sql()


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in SCHEMAS:
        path = f"{sf}/{t}.parquet"
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return c


def rows(cols, data):
    order = sorted(range(len(cols)), key=lambda i: cols[i])
    return sorted(tuple(repr(round(r[i], 6) + 0.0) if isinstance(r[i], float) else repr(r[i]) for i in order) for r in data)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(name, spark, sf, con):
    got, want = QUERIES[name](spark, sf), con.sql(ORACLES[name])
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got.columns, [tuple(r) for r in got.collect()]) == rows(want.columns, want.fetchall())


def test_names_are_unique_and_oracles_have_queries():
    assert set(ORACLES) <= set(QUERIES)


def test_flagship(spark, sf):
    out = catalogue.flagship(spark, sf)
    assert out.count() > 0 and out.columns[0] == "id"
