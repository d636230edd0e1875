"""Queries with SQL give the rows that the SQL gives."""

import os

import duckdb
import pytest

from textmill.llm import registry


@pytest.mark.parametrize("name", sorted(registry.ORACLE))
def test_same_rows(spark, sf, name):
    c = duckdb.connect()
    for f in os.listdir(sf):
        c.execute(f"CREATE VIEW {f[:-8]} AS SELECT * FROM '{sf}/{f}'")
    df = registry.QUERIES[name](spark, sf)
    cur = c.execute(registry.ORACLE[name])
    names = [x[0] for x in cur.description]
    assert sorted(df.columns) == sorted(names)
    assert sorted(tuple(r[n] for n in names) for r in df.collect()) == sorted(cur.fetchall())


def test_every_query_is_registered():
    assert {n.split("_")[0] for n in registry.QUERIES} == {f"op{i}" for i in range(1, 11)}
