from __future__ import annotations

import corpus_pipeline
from rowloom.llm import decontam, neardup, quality, toxicity


def test_stages_take_effect(spark, sf, documents, model_path):
    labels, benchmark = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("labels", "benchmark"))
    docs = documents
    good = {r["doc_id"] for r in quality.score(docs, quality.train(docs, labels)).where("predicted = 1").collect()}
    docs = corpus_pipeline.quality_stage(spark, docs, sf)
    assert docs.columns == documents.columns and {r["doc_id"] for r in docs.collect()} == good
    clean = {r["doc_id"] for r in toxicity.score(docs, toxicity.train(docs, labels)).where("predicted = 0").collect()}
    docs = corpus_pipeline.toxicity_stage(spark, docs, sf)
    assert docs.columns == documents.columns and {r["doc_id"] for r in docs.collect()} == clean
    unique = {r["doc_id"] for r in neardup.near_duplicates(docs, threshold=80).where("kept").collect()}
    docs = corpus_pipeline.neardup_stage(spark, docs, sf)
    assert docs.columns == documents.columns and {r["doc_id"] for r in docs.collect()} == unique
    fresh = {r["doc_id"] for r in decontam.find_contamination(docs, benchmark).where("size(spans) = 0").collect()}
    docs = corpus_pipeline.decontamination_stage(spark, docs, sf)
    assert docs.columns == documents.columns and {r["doc_id"] for r in docs.collect()} == fresh
    last = corpus_pipeline.run(spark, sf)
    assert {r["doc_id"] for r in last.select("doc_id").collect()} == fresh


def test_stages_bear_odd_and_no_rows(spark, sf, odd_docs, no_docs):
    for given in (odd_docs, no_docs):
        docs = given
        for name, stage in corpus_pipeline.STAGES:
            before = {r["doc_id"] for r in docs.select("doc_id").collect()}
            out = stage(spark, docs, sf).cache()
            assert {r["doc_id"] for r in out.select("doc_id").collect()} <= before
            if name != "encoding":
                assert out.columns == given.columns
            else:
                assert out.count() == docs.count()
            docs = out
    assert docs.count() == 0


def test_repeated_rows_are_one_document(spark, sf, odd_docs):
    """A row that repeats a kept id stays with it; a copy under another id goes; null texts are no copies."""
    kept = corpus_pipeline.neardup_stage(spark, odd_docs, sf).collect()
    assert sorted(r["doc_id"] for r in kept if r["doc_id"] in (0, 1, 2, 5, 6, 10, 11)) == [0, 1, 2, 5, 5, 10]


def test_near_copies_from_080_leave(spark, sf):
    """Sharing 16 of 20 shingles is a near copy here, 15 of 20 is not."""
    words = [f"a{i}" for i in range(24)]
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(words[:20])), (3, " ".join(words[:19] + ["b"] * 5))], "doc_id long, text string")
    assert {r["doc_id"] for r in corpus_pipeline.neardup_stage(spark, docs, sf).collect()} == {1, 3}
