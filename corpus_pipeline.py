"""The corpus pipeline: five stages over documents, each on all that the one before kept.

A run writes every stage's rows as Parquet in the shared folder of the session
(spark.checkpoint.dir) and reads them again as the next stage's documents.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutloom.llm import mixing, near_copies, quality, secrets, sentencepiece_codec
from cutloom.llm.common import shared_folder


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base or whose posterior is below one half go."""
    return quality.quality_filtered(docs)


def dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays, that with the smallest id.

    Candidates are documents whose SimHash fingerprints differ in at most 4 bits,
    and those that share a MinHash band, since 4 bits miss most pairs of a
    similarity of 0.8.  Links are the candidates' pairs whose sets of five-word
    shingles have a similarity of 0.8 or more.
    """
    return near_copies.deduplicated(docs, size=5)


def secrets_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by their kind; n_chars follows."""
    return secrets.redacted(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the budget of their source draws them."""
    return mixing.mixed(docs)


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, ids) of each document drawn."""
    import public_tokenizers

    return sentencepiece_codec.encoded(docs, public_tokenizers.path("piece_bpe_32k.model")).select(F.col("id").alias("doc_id"), "ids")


STAGES = [("quality rules", quality_stage), ("simhash near-dedup", dedup_stage), ("secret scans", secrets_stage), ("mixing sources", mixing_stage), ("sentencepiece", encoding_stage)]

#: SQL can't express the stages; tests/llm/test_pipeline_stages.py and test_near_copies.py hold each against plain Python, as called here.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply the stages to documents."""
    folder = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
    return docs
