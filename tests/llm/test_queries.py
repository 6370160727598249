import duckdb
import pytest

import corpus_pipeline
from fewrounds.llm import queries

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", list(queries.oracle_sql()))
def test_equals_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = queries.queries()[name](spark, SF)
    columns = sorted(df.columns)
    cur = con.execute(queries.oracle_sql()[name])
    at = {d[0]: k for k, d in enumerate(cur.description)}
    assert sorted(str(tuple(r[c] for c in columns)) for r in df.collect()) == sorted(str(tuple(r[at[c]] for c in columns)) for r in cur.fetchall())


def test_pipeline(spark):
    rows = corpus_pipeline.run(spark, SF)
    assert rows.where("lossless").count() == rows.count() > 100
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "near_duplicates", "benchmark_passages", "personal_data", "sentence_pieces"]
