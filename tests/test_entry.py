"""Every query with SQL equals DuckDB on the smallest tables, for a spread of the families."""

import duckdb
import pytest

import __spark_entry__ as entry
from fewrounds.queries import QUERIES, SQL
from fewrounds.sources.tables import TABLES

SF = "/root/testdata/sf0.001"
NAMES = [n for n in SQL if n.split("_")[0] in ("join", "agg", "window", "set", "scalar", "topk", "filter", "source", "params", "stream", "cut", "st", "nested", "proxy", "global", "contract", "graph", "sink", "function")]


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_equals_sql(spark, db, name):
    df = QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    mine = sorted(str(tuple(r[c] for c in columns)) for r in df.collect())
    cur = db.execute(SQL[name])
    at = {d[0]: k for k, d in enumerate(cur.description)}
    assert sorted(at) == columns
    assert mine == sorted(str(tuple(r[at[c]] for c in columns)) for r in cur.fetchall())


def test_entry(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
