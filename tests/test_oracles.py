"""Every registered query with SQL gives DuckDB's rows on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
ORACLES = entry.oracle_sql()


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    return con


def normal(x):
    return round(x, 9) if isinstance(x, float) else x


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(name, spark, small, duck):
    df = entry.queries()[name](spark, small)
    columns = sorted(df.columns)
    own = sorted(repr([normal(r[c]) for c in columns]) for r in df.collect())
    result = duck.execute(ORACLES[name])
    names = [c[0] for c in result.description]
    assert sorted(names) == columns
    at = [names.index(c) for c in columns]
    assert own == sorted(repr([normal(r[i]) for i in at]) for r in result.fetchall())


def test_entry(spark):
    assert entry.entry(spark).columns == ["o_orderkey", "value"]
