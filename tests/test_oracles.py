"""Every registered query that SQL can express, against DuckDB on the smallest tables."""

from __future__ import annotations

import math
import re

import duckdb
import pandas as pd
import pytest

from nbflow import registry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v):
    if v is None or isinstance(v, float) and math.isnan(v):
        return None
    if hasattr(v, "isoformat"):
        return str(pd.Timestamp(v))
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    return v


@pytest.fixture(scope="session")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_sql(spark, duck, name):
    ours = registry.queries()[name](spark, SF)
    theirs = duck.execute(registry.oracle_sql()[name])
    columns = [c[0] for c in theirs.description]
    assert sorted(ours.columns) == sorted(columns)
    order = sorted(columns)
    a = sorted((tuple(plain(r[c]) for c in order) for r in ours.collect()), key=repr)
    b = sorted((tuple(plain(r[columns.index(c)]) for c in order) for r in theirs.fetchall()), key=repr)
    assert a == b


def test_names_are_no_numbered_operators():
    assert not [n for n in registry.queries() if re.match(r"op\d+_", n)]


def test_every_oracle_has_its_query():
    assert set(registry.oracle_sql()) <= set(registry.queries())
