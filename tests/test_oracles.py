"""Queries against their SQL twins on the small tables."""

from __future__ import annotations

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"op7_quality_rules"}


@pytest.fixture(scope="module")
def con(small):
    c = duckdb.connect()
    c.execute("SET timezone = 'UTC'")
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return c


def plain(v):
    return round(float(v), 9) + 0.0 if isinstance(v, float) or type(v).__name__ == "Decimal" else v


CORE = sorted(k for k in entry.oracle_sql() if not k.startswith(("op", "pipeline")))


@pytest.mark.parametrize("name", CORE)
def test_query_equals_sql(spark, con, small, name):
    df = entry.queries()[name](spark, small)
    found = con.execute(entry.oracle_sql()[name])
    names = [d[0] for d in found.description]
    assert sorted(names) == sorted(df.columns)
    order = sorted(names)
    want = sorted(repr([plain(row[names.index(c)]) for c in order]) for row in found.fetchall())
    got = sorted(repr([plain(row[c]) for c in order]) for row in df.collect())
    assert got == want


def test_registry_is_complete():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    out = entry.entry(spark)
    assert out.columns and out.count() > 0
