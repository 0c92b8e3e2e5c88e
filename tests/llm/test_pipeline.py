"""The pipeline and the registered text queries."""

import corpus_pipeline
import pytest
from conftest import same

from treeline.llm import queries


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_twin(spark, duck, small, name):
    left, right = same(queries.queries()[name](spark, small), duck, queries.oracle_sql()[name])
    assert left == right


def test_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    odd = spark.createDataFrame([(10**6, None, None, None, None), (10**6 + 1, "", "en", "a", 0), (10**6 + 1, "", "en", "a", 0)], docs.schema)
    columns, rows = docs.columns, docs.union(odd)
    import tempfile

    base = tempfile.mkdtemp()
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        rows.write.parquet(f"{base}/{i}")
        before = spark.read.parquet(f"{base}/{i}")
        rows = stage(spark, before, small)
        if i < len(corpus_pipeline.STAGES) - 1:
            assert rows.columns == columns, name
    assert rows.where("taken <= 0").count() == 0 and rows.count() == rows.select("doc_id").distinct().count()


def test_run_drops_what_it_should(spark, small):
    kept = {r.doc_id for r in corpus_pipeline.run(spark, small).collect()}
    from treeline.llm.near_dedup import near_duplicates

    docs = spark.read.parquet(f"{small}/documents.parquet")
    by: dict = {}
    for r in near_duplicates(docs, 5, 80).collect():
        by.setdefault(r.component_id, set()).add(r.doc_id)
    assert all(len(kept & group) <= 1 for group in by.values())
    bad = {r.doc_id for r in queries.queries()["op6_decontaminate"](spark, small).where("contaminated").collect()}
    assert not kept & bad
