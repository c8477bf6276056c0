"""The pipeline's stages on the smallest documents: what each keeps, against plain Python."""

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")


def test_stages_keep_columns_and_decide(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    columns, kept = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, data)
        assert docs.columns == columns, name
        now = docs.count()
        assert 0 < now <= kept, name
        kept = now
    items = [r["text"] for r in spark.read.parquet(f"{data}/benchmark.parquet").collect()]
    texts = [r["text"] for r in docs.collect()]
    assert not any(i in t for i in items for t in texts if t)
