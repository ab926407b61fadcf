"""What a chain of jobs leaves on the disk that driver and executors share."""

from pathlib import Path

from rangekeep.llm import _shared, ngram_join


def _held(spark, before=()):
    root = Path(_shared.shared_folder(spark).removeprefix("file:"))
    return {p.name for p in root.glob("t-*")} - set(before)


def test_link_leaves_its_result_alone(spark):
    rows = [(i, " ".join(f"w{(i // 3) * 50 + j}" for j in range(40)) + (" x" if i % 3 else "")) for i in range(300)]
    before = _held(spark)
    out = ngram_join.link(spark.createDataFrame(rows, "doc_id long, text string"))
    assert len(_held(spark, before)) == 1
    assert {r.doc_id: r.component_id for r in out.collect()} == {i: i // 3 * 3 for i in range(300)}


def test_pipeline_leaves_what_its_last_stage_reads(spark, data):
    import corpus_pipeline

    before = _held(spark)
    out = corpus_pipeline.run(spark, data)
    n = out.count()
    # the documents that it packs and two tables of its own
    assert n > 0 and len(_held(spark, before)) <= 3


def test_sent_keys_meet_in_turns(spark, monkeypatch):
    """A turn's plan holds its part of the keys, the parts together are the buckets of one turn, and links stay the same."""
    rows = [(i, " ".join(f"w{(i // 3) * 50 + j}" for j in range(40)) + (" x" if i % 3 else "")) for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    sent = spark.createDataFrame([(i % 50 - 25, i) for i in range(200)] + [(100 + i, i) for i in range(200)], "key long, s1 long")
    tell = lambda parts: sorted(tuple(r) for p in parts for r in p.collect())
    whole, parts = list(ngram_join._buckets(sent, 1)), list(ngram_join._buckets(sent, 5))
    assert len(whole) == 1 and len(parts) == 5 and tell(whole) == tell(parts) and len(tell(parts)) == 200
    assert [{r.key % 5 for r in p.collect()} for p in parts] == [{i} for i in range(5)]
    monkeypatch.setattr(ngram_join, "KEYS_AT_ONCE", 100)
    assert {r.doc_id: r.component_id for r in ngram_join.link(df).collect()} == {i: i // 3 * 3 for i in range(300)}
