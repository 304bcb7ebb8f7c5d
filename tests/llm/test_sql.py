import duckdb
import pytest

from tagroute.llm import entry

SMALL = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(entry.ORACLE_SQL))
def test_against_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "benchmark", "labels", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SMALL}/{t}.parquet')")
    got = entry.QUERIES[name](spark, SMALL)
    said = con.execute(entry.ORACLE_SQL[name])
    columns = [c[0] for c in said.description]
    assert sorted(columns) == sorted(got.columns)
    assert sorted(map(repr, (tuple(r) for r in got.select(*columns).collect()))) == sorted(map(repr, said.fetchall()))
