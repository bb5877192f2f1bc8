"""Every query of the engine with a SQL equivalent gives the same rows in DuckDB."""

import datetime
import os

import duckdb
import pytest

from neardup.plans import QUERIES, SQL


def plain(v):
    if isinstance(v, float):
        return round(v, 5) + 0.0
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None).isoformat()
    return v


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.sql(f"create view {f.split('.')[0]} as select * from '{sf}/{f}'")
    return c


@pytest.mark.parametrize("name", sorted(SQL))
def test_same_rows(spark, sf, con, name):
    df = QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    ours = [tuple(plain(r[c]) for c in cols) for r in df.collect()]
    res = con.execute(SQL[name])
    names = [d[0] for d in res.description]
    assert sorted(names) == cols
    theirs = [tuple(plain(dict(zip(names, r, strict=True))[c]) for c in cols) for r in res.fetchall()]
    assert sorted(map(repr, ours)) == sorted(map(repr, theirs))
