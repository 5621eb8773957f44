import corpus_pipeline
from test_operators import brute_components

from pathq.llm.common import Workspace


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, now = docs.columns, docs
    for name, stage in corpus_pipeline.STAGES:
        before = {r["doc_id"]: r for r in now.collect()}
        out = Workspace(spark, "test").table(stage(spark, now, sf), name)
        rows = out.collect()
        ids = [r["doc_id"] for r in rows]
        assert set(ids) <= set(before)
        if name != corpus_pipeline.STAGES[-1][0]:
            assert out.columns == columns
        if name == "language":
            assert all(not any(c.isalpha() for c in before[i]["text"] or "") or len(before[i]["text"]) < 40 for i in set(before) - set(ids))
        if name == "near_dedup":
            comp = brute_components([(i, r["text"]) for i, r in before.items()], 5)
            assert sorted(ids) == sorted({comp[i] for i in comp})
        if name == "mixture":
            assert max(ids.count(i) for i in ids) <= 2
        if name == "packing":
            assert len(rows) == sum(1 for _ in now.collect())
        now = out


def test_repeated_rows_leave_one(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(20)
    twice = docs.union(docs.limit(5))
    assert corpus_pipeline.near_dedup(spark, twice, sf).count() == corpus_pipeline.near_dedup(spark, docs, sf).count()
    assert corpus_pipeline.near_dedup(spark, docs.limit(0), sf).count() == 0


def test_run(spark, sf):
    assert corpus_pipeline.run(spark, sf).count() > 0
