"""Queries against their SQL twins, and the pipeline against its stages."""

import pytest

import corpus_pipeline
from conftest import SF
from repeatfold.llm import queries


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_twin(name, same):
    same(queries.queries()[name], queries.oracle_sql()[name])


def test_pipeline(spark):
    from repeatfold.llm.common import cut, table

    docs = table(spark, SF, "documents")
    counts = []
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        docs = cut(stage(spark, docs, SF))
        counts.append(docs.count())
        assert k == len(corpus_pipeline.STAGES) - 1 or set(docs.columns) == set(corpus_pipeline.COLUMNS)
    assert counts[0] >= counts[1] == counts[2] >= counts[3] > 0
    got = corpus_pipeline.run(spark, SF)
    assert sorted(map(tuple, got.select("doc_id", "start", "ids_crc32").collect())) == sorted(map(tuple, docs.select("doc_id", "start", "ids_crc32").collect()))
