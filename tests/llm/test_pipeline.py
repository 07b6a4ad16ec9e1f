import corpus_pipeline
import pytest

from tests.llm import edge
from windowjoin.llm import common
from windowjoin.llm import queries as llm

SF = "/root/testdata/sf0.001"


def test_stages_and_registration():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "near_duplicates", "repeats", "packing"]
    assert corpus_pipeline.ORACLE_SQL is None
    names = llm.queries()
    assert "pipeline" in names and all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11))


def test_run(spark):
    docs = common.read_documents(spark, SF)
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        n = docs.count()
        docs = common.written(stage(spark, docs, SF), name)
        assert docs.columns == columns and 0 < docs.count() <= n
    assert docs.filter("n_chars <> length(text)").isEmpty()
    assert docs.select("doc_id").distinct().count() == docs.count()
    packed = corpus_pipeline.run(spark, SF)
    assert packed.select("doc_id").distinct().count() == docs.count()
    totals = packed.groupBy("doc_id").agg({"length": "sum", "doc_tokens": "max"})
    assert totals.filter("`sum(length)` <> `max(doc_tokens)`").isEmpty()


@pytest.mark.parametrize("make", [edge.table, edge.with_repeats, edge.empty])
def test_stages_on_edges(spark, make):
    docs = make(spark)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns
        docs = common.written(out, name)
    assert corpus_pipeline.STAGES[-1][1](spark, docs, SF).count() >= docs.count()
