"""Every query with an oracle agrees with DuckDB on the smallest tables; the rest return rows."""

import datetime as dt

import duckdb
import pytest

from hypernear import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def views(sf_dir):
    con = duckdb.connect()
    for table in TABLES:
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{sf_dir}/{table}.parquet'")
    return con


def plain(value):
    if isinstance(value, list):
        return tuple(map(plain, value))
    return value.replace(tzinfo=None) if isinstance(value, dt.datetime) else value


@pytest.mark.parametrize("name", sorted(catalog.QUERIES))
def test_query(spark, views, sf_dir, name):
    found = catalog.QUERIES[name](spark, sf_dir)
    columns = sorted(found.columns)
    rows = sorted((tuple(plain(r[c]) for c in columns) for r in found.collect()), key=repr)
    if name not in catalog.ORACLES:
        assert rows
        return
    result = views.execute(catalog.ORACLES[name])
    names = [c[0] for c in result.description]
    assert sorted(names) == columns
    want = sorted((tuple(plain(r[names.index(c)]) for c in columns) for r in result.fetchall()), key=repr)
    assert rows == want
