"""The pipeline's stages and the queries of the operators on the smallest tables."""

import importlib.util

import pytest

from objdelta.llm import queries


def test_names():
    assert {n.split("_")[0] for n in queries.QUERIES if n.startswith("op")} == {f"op{i}" for i in range(1, 11)}


@pytest.mark.skipif(importlib.util.find_spec("corpus_pipeline") is None, reason="no pipeline")
def test_stages_keep_columns_and_take_effect(spark, sf):
    import corpus_pipeline
    from objdelta.llm.common import Workspace, read_table

    docs = read_table(spark, sf, "documents")
    columns, work = docs.columns, Workspace(spark, "t")
    sizes = [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = work.table(stage(spark, docs, sf), name)
        assert docs.columns == columns
        sizes.append(docs.count())
    assert sizes[1] <= sizes[0] and sizes[2] == sizes[1] and sizes[3] < sizes[2] and sizes[4] < sizes[3]
    last = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert {r.doc_id for r in last.select("doc_id").collect()} == {r.doc_id for r in docs.select("doc_id").collect()}
    assert corpus_pipeline.run(spark, sf).agg({"length": "sum"}).first()[0] == last.agg({"length": "sum"}).first()[0]
