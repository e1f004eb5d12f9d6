"""The pipeline keeps what its stages should and works from stage to stage."""

import corpus_pipeline


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = docs
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, kept, sf)
        if name != "sentencepiece":
            assert out.columns == docs.columns
            assert {r.doc_id for r in out.select("doc_id").collect()} <= {r.doc_id for r in kept.select("doc_id").collect()}
        kept = out
    assert kept.count() > 0.5 * docs.count()
