"""The pipeline's stages on a small table with planted cases."""

import corpus_pipeline
from trajdp.llm import jaccard_join, packing
from trajdp.llm.storage import written


def test_stages(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        docs = written(stage(spark, docs, data), f"test-{name}")
        if name != "packing":
            assert docs.columns == columns and docs.dtypes == before.dtypes
            assert 0 < docs.count() <= before.count()
        if name == "near_duplicates":
            left = jaccard_join.near_duplicates(docs)
            assert left.where("n_shingles > 0 and doc_id <> component_id").count() == 0
    assert docs.select("doc_id").distinct().count() == before.select("doc_id").distinct().count()
    assert docs.columns == packing.packed(before).columns


def test_empty_documents(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet").where("false")
    for _, stage in corpus_pipeline.STAGES:
        docs = written(stage(spark, docs, data), "test-empty")
        assert docs.count() == 0
