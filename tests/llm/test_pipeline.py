"""The stages of the corpus pipeline on the smallest tables."""

import duckdb
import pytest

import corpus_pipeline
from graphweld.llm import queries


def test_stages(spark, tiny_dir, tmp_path):
    docs = first = spark.read.parquet(f"{tiny_dir}/documents.parquet")
    counts = []
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, tiny_dir)
        out.write.parquet(f"{tmp_path}/{name}")
        docs = spark.read.parquet(f"{tmp_path}/{name}")
        counts.append(docs.count())
        if name != corpus_pipeline.STAGES[-1][0]:
            assert docs.columns == first.columns
    assert 0 < counts[1] <= counts[0] < first.count() and counts[2] == counts[1]


def test_registered():
    assert sorted(int(n[2:].split("_")[0]) for n in queries.queries()) == list(range(1, 11))


@pytest.mark.parametrize("name", sorted(queries.ORACLE))
def test_same_as_sql(spark, tiny_dir, name):
    duck = duckdb.connect()
    for t in ("documents", "pages"):
        duck.sql(f"CREATE VIEW {t} AS SELECT * FROM '{tiny_dir}/{t}.parquet'")
    df, want = queries.queries()[name](spark, tiny_dir), duck.sql(queries.ORACLE[name])
    columns = sorted(df.columns)
    assert columns == sorted(want.columns)
    rows = lambda found: sorted(map(repr, found))
    assert rows(tuple(r) for r in df.select(*columns).collect()) == rows(want.select(*columns).fetchall())
