"""The pipeline's stages against the operators' plain versions, stage by stage."""

import pytest

pytest.importorskip("cutloom.llm")
corpus_pipeline = pytest.importorskip("corpus_pipeline")

SF = "/root/testdata/sf0.001"


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, seen = docs.columns, []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, SF)
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == columns, name
        out.write.parquet(str(tmp_path / str(k)))
        docs = spark.read.parquet(str(tmp_path / str(k)))
        seen.append(docs.count())
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality rules", "simhash near-dedup", "secret scans", "mixing sources", "sentencepiece"]
    assert seen[0] > seen[1] == seen[2] >= 1 and docs.columns == ["doc_id", "ids"] and seen[4] == seen[3]


def test_run_equals_stages(spark):
    a = corpus_pipeline.run(spark, SF).collect()
    b = corpus_pipeline.run(spark, SF).collect()
    assert sorted((r["doc_id"], tuple(r["ids"])) for r in a) == sorted((r["doc_id"], tuple(r["ids"])) for r in b) and a


def test_empty_and_odd_documents(spark):
    schema = spark.read.parquet(f"{SF}/documents.parquet").schema
    for rows in ([], [(1, None, None, None, None), (1, None, None, None, None), (None, "x " * 40, "en", "src1", 80), (2, "", "en", "src1", 0)]):
        docs = spark.createDataFrame(rows, schema)
        for _, stage in corpus_pipeline.STAGES:
            docs = stage(spark, docs, SF)
        docs.collect()
