"""The pipeline stage by stage against brute force on a small corpus with planted cases."""

from collections import Counter

import corpus_pipeline as pipeline
from tests_llm_data import corpus


def test_stages(spark, tmp_path):
    sf = corpus(spark, str(tmp_path))
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = []
    for k, (name, stage) in enumerate(pipeline.STAGES):
        out = stage(spark, docs, sf)
        out.write.parquet(f"{tmp_path}/{k}")
        docs = spark.read.parquet(f"{tmp_path}/{k}")
        assert docs.columns[:6] == ["doc_id", "text", "lang", "source", "n_chars", "row"], name
        kept.append({r.doc_id for r in docs.collect()})
    assert not kept[0] & set(range(100, 120)) and set(range(60)) <= kept[0]
    assert kept[1] & {200, 201, 202, 203} == {200} and set(range(60)) <= kept[1]
    assert not kept[2] & {300, 301} and set(range(60)) <= kept[2]
    assert not docs.where("text like '%4111111111111111%'").count()
    copies = Counter(r.doc_id for r in docs.collect())
    assert max(copies.values()) <= 2
    assert [n for n, _ in pipeline.STAGES] == ["toxicity", "near_duplicates", "decontamination", "pii", "mixing"]


def test_empty_tables(spark, tmp_path):
    sf = corpus(spark, str(tmp_path))
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, stage in pipeline.STAGES:
        docs = stage(spark, docs, sf)
        assert docs.count() == 0
