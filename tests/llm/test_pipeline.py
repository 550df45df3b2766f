"""The pipeline's stages, one after the other."""

import corpus_pipeline as P


def test_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    n = docs.count()
    for name, stage in P.STAGES[:-1]:
        docs = P.written(stage(spark, docs, small), name)
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        assert 0.7 * n < docs.count() <= n
    packed = P.STAGES[-1][1](spark, docs, small)
    assert {r["doc_id"] for r in packed.select("doc_id").collect()} == {r["doc_id"] for r in docs.select("doc_id").collect()}
