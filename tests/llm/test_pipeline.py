"""The pipeline's stages keep columns, take effect, and end in sequences."""

from __future__ import annotations

import corpus_pipeline
from coloc.llm.tables import staged
from tests.conftest import DATA


def test_stages(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    n = docs.count()
    names = [name for name, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "quality_model", "near_dedup", "packing"]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = staged(stage(spark, docs, DATA), "stage")
        assert out.columns == docs.columns and 0 < out.count() <= n
        docs, n = out, out.count()
    assert n < spark.read.parquet(f"{DATA}/documents.parquet").count()
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, DATA)
    assert {r[0] for r in pieces.select("doc_id").distinct().collect()} == {r[0] for r in docs.select("doc_id").collect()}
