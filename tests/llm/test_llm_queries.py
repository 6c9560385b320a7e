import duckdb
import pytest

import corpus_pipeline
from conftest import same_rows
from querymarks.llm import exact_dedup, registry


@pytest.mark.parametrize("name", registry.oracle_sql())
def test_query_against_sql(spark, small, duck, name):
    same_rows(registry.queries()[name](spark, small), duck, registry.oracle_sql()[name])


@pytest.mark.parametrize("name", [k for k in registry.queries() if k not in registry.oracle_sql() and k != "pipeline"])
def test_query_runs_on_whole_table(spark, small, name):
    table = {"op7": "pages"}.get(name.split("_")[0], "documents")
    out = registry.queries()[name](spark, small)
    if name.startswith("op8"):
        assert out.count() > 0
    else:
        assert out.count() == duckdb.sql(f"SELECT count(*) FROM '{small}/{table}.parquet'").fetchall()[0][0]


def test_pipeline_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    whole = {r["doc_id"] for r in docs.select("doc_id").collect()}
    kept = None
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, small)
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == docs.columns, name
        now = {r["doc_id"] for r in out.select("doc_id").collect()}
        assert now <= (kept if kept is not None else whole), name
        if name == "exact_dedup":
            groups = exact_dedup.exact_groups(docs).collect()
            assert now == {r["keep_id"] for r in groups}
        kept, docs = now, (out if k == len(corpus_pipeline.STAGES) - 1 else spark.createDataFrame(out.collect(), out.schema))
    assert kept
    assert {r["doc_id"] for r in corpus_pipeline.run(spark, small).collect()} == kept
