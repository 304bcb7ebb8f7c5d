"""Spark against DuckDB on the smallest tables, for every query that is quick there."""

import duckdb
import pytest

import __spark_entry__
from tagroute.registry import ORACLE_SQL, QUERIES
from tagroute.sources.tables import TABLES

SLOW = ("topk_batch", "m_effectiveness")


def _plain(v):
    if isinstance(v, float):
        return round(v, 6) + 0.0
    return tuple(map(_plain, v)) if isinstance(v, list) else v


@pytest.mark.parametrize("name", [n for n in ORACLE_SQL if n not in SLOW])
def test_against_sql(spark, sf_dir, name):
    con = duckdb.connect()
    con.execute("SET memory_limit = '2GB'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    df = QUERIES[name](spark, sf_dir)
    columns = sorted(df.columns)
    got = sorted((tuple(_plain(r[c]) for c in columns) for r in df.collect()), key=repr)
    result = con.execute(ORACLE_SQL[name])
    names = [d[0] for d in result.description]
    assert sorted(names) == columns
    expected = sorted((tuple(_plain(r[names.index(c)]) for c in columns) for r in result.fetchall()), key=repr)
    assert got == expected


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() > 0


def test_every_oracle_has_a_query():
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
