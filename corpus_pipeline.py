"""The corpus pipeline: quality rules, near-duplicates, benchmark contamination, secrets, tokens.

Each stage takes the documents that the stage before it left, with their columns, and its decisions take effect there:
rejected documents, all but one of a class of near-duplicates and contaminated documents go; confirmed secrets are
replaced in the text; the last stage returns the token ids of what is left.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from proxcore.llm import bpe, decontaminate, near_duplicates, quality, secrets
from proxcore.llm.common import keep, read


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.drop_low_quality(docs)


def near_duplicate_removal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_duplicates.drop_near_duplicates(docs)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.drop_contaminated(docs, read(spark, sf_dir, "benchmark"))


def secret_redaction(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    words = secrets.vocabulary(docs)
    return secrets.redact(docs, secrets.train(secrets.labelled_findings(spark), words), words)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.round_trip(docs.select("doc_id", "text"), with_ids=True).select("doc_id", "trip.*")


STAGES = [
    ("quality rules", quality_rules), ("near-duplicates", near_duplicate_removal), ("decontamination", benchmark_decontamination),
    ("secrets", secret_redaction), ("tokens", tokens),
]

#: The forest, the robust estimates and the BPE merges are beyond SQL. tests/llm holds the operators against plain versions; of the
#: stages together it looks at row counts and columns.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = keep(docs)
    return docs
