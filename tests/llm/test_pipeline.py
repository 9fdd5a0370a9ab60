"""The pipeline, stage by stage."""

import corpus_pipeline
from proxcore.llm import bpe
from proxcore.llm.common import keep

SF = "/root/testdata/sf0.001"


def test_stages_take_effect(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, sizes = docs.columns, [docs.count()]
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        docs = keep(stage(spark, docs, SF))
        sizes.append(docs.count())
        assert k == len(corpus_pipeline.STAGES) - 1 or docs.columns == columns
    assert sizes[0] > sizes[1] > sizes[2] > sizes[3] == sizes[4] == sizes[5] > sizes[0] / 2
    assert docs.select("doc_id").distinct().count() == sizes[-1] and "decoded_sha256" in docs.columns


def test_an_empty_corpus(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = keep(stage(spark, docs, SF))
    assert docs.count() == 0


def test_each_stage_is_named():
    assert [name for name, _ in corpus_pipeline.STAGES] == ["quality rules", "near-duplicates", "decontamination", "secrets", "tokens"] and bpe.FILE
