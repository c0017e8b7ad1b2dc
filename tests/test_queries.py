"""Registered queries against their SQL definitions on the smallest tables."""

import datetime
import math

import pytest

duckdb = pytest.importorskip("duckdb")

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(value):
    if isinstance(value, float):
        return "nan" if math.isnan(value) else repr(round(value, 9))
    if isinstance(value, datetime.datetime):
        return value.isoformat()
    return str(value)


@pytest.fixture(scope="module")
def connection(sf):
    con = duckdb.connect()
    for name in TABLES:
        con.execute(f"create view {name} as select * from '{sf}/{name}.parquet'")
    return con


def names():
    from thriftline import registry

    return list(registry.QUERIES)


@pytest.mark.parametrize("name", names())
def test_query(spark, sf, connection, name):
    from thriftline import registry

    df = registry.QUERIES[name](spark, sf)
    columns, rows = df.columns, [tuple(r) for r in df.collect()]
    if name not in registry.ORACLES:
        assert rows
        return
    result = connection.execute(registry.ORACLES[name])
    wanted = [c[0] for c in result.description]
    assert sorted(columns) == sorted(wanted)
    order = sorted(columns)
    ours = sorted(tuple(plain(r[columns.index(c)]) for c in order) for r in rows)
    theirs = sorted(tuple(plain(r[wanted.index(c)]) for c in order) for r in result.fetchall())
    assert ours == theirs


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 1
    assert set(entry.oracle_sql()) <= set(entry.queries())
