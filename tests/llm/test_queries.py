"""The registered text-corpus queries on the smallest tables, and the pipeline stage by stage."""

from collections import Counter

import pytest
from conftest import same

import corpus_pipeline
from rangekeep.llm import registry


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_sql(spark, data, duck, name):
    assert same(registry.queries()[name](spark, data).toPandas(), duck(registry.oracle_sql()[name], data))


@pytest.mark.parametrize("name,table", [("op1_toxicity", "documents"), ("op2_ngram_join", "documents"), ("op3_html_text", "pages"), ("op4_quality", "documents"), ("op5_packing", "documents"), ("op7_secrets", "documents"), ("op8_url_filter", "pages"), ("op9_lattice", "embeddings")])
def test_a_row_each(spark, data, name, table):
    assert registry.queries()[name](spark, data).count() == spark.read.parquet(f"{data}/{table}.parquet").count()


def test_pipeline(spark, data):
    from rangekeep.llm import mixing, ngram_join, toxicity
    from rangekeep.llm._shared import keep

    docs = spark.read.parquet(f"{data}/documents.parquet")
    got = {}
    for name, stage in corpus_pipeline.STAGES:
        after = stage(spark, docs, data)
        if name != "packing":
            assert after.columns == docs.columns
        got[name] = (docs, after := keep(after))
        docs = after
    a, b = got["toxicity"]
    assert b.count() <= a.count() and toxicity.score(b, toxicity.learn([], __import__("numpy").zeros(0))).count() == b.count()
    a, b = got["near_copies"]
    want = [r.doc_id for r in ngram_join.link(a, k=5, num=80).collect() if r.doc_id == r.component_id]
    assert sorted(r.doc_id for r in b.collect()) == sorted(set(want))
    a, b = got["mixing"]
    copies = {r.doc_id: r.copies for r in mixing.mix(a).collect() if r.copies}
    assert Counter(r.doc_id for r in b.collect()) == copies
    a, b = got["packing"]
    assert Counter(r.doc_id for r in a.collect()) == Counter(r.doc_id for r in b.collect())
    assert "pipeline" in corpus_pipeline.queries()
