"""The pipeline's quality stage keeps what operator 5 predicts as good."""

import corpus_pipeline
from graphsieve.llm import quality


def test_stage_uses_the_operators_threshold(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    used = []

    def scored(rows, weights, threshold=quality.THRESHOLD):
        used.append(threshold)
        return quality.score_quality(rows, weights, threshold)

    monkeypatch.setattr(corpus_pipeline, "score_quality", scored)
    kept = {r.doc_id for r in corpus_pipeline.quality(spark, docs, sf).collect()}
    rows = quality.quality_scores(docs, spark.read.parquet(f"{sf}/labels.parquet")).collect()
    assert used == [quality.THRESHOLD] and kept == {r.doc_id for r in rows if r.predicted}
