"""Every query with an oracle against DuckDB, on the smallest tables; every other one gives rows."""

import os

import duckdb
import pytest

from diversify import queries

DIR = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(DIR), reason="no test tables here")


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in os.listdir(DIR):
        con.execute(f"CREATE VIEW {t[:-8]} AS SELECT * FROM '{DIR}/{t}'")
    return con


def plain(x):
    return round(x, 6) if isinstance(x, float) else x


@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_oracle(spark, duck, name):
    found = queries.QUERIES[name](spark, DIR)
    columns = sorted(found.columns)
    rel = duck.execute(queries.SQL[name])
    names = [c[0] for c in rel.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    want = sorted(repr(tuple(plain(r[i]) for i in at)) for r in rel.fetchall())
    got = sorted(repr(tuple(plain(r[c]) for c in columns)) for r in found.collect())
    assert got == want


@pytest.mark.parametrize("name", sorted(set(queries.QUERIES) - set(queries.SQL)))
def test_rows(spark, name):
    assert queries.QUERIES[name](spark, DIR).count() > 0
