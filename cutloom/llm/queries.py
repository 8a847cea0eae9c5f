"""The operators bound to the given tables, one query each, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutloom.llm import chat, lm_score, mixing, quality, secrets, sentencepiece_codec, simhash, token_count, topk, url_filter
from cutloom.llm.common import table


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_score.backoff_scores(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = quality.judged(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select(F.col("doc_id").cast("long").alias("doc_id"), *[F.col(f"__q.m.{c}").alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")], F.col("__q.base_failed").alias("base_failed"), F.col("__kept").alias("kept"))


def op3_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sentencepiece_codec.digests(table(spark, sf_dir, "documents"), tokenizer_path("piece_bpe_32k.model")).withColumnRenamed("id", "doc_id")


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = simhash.near_duplicates(table(spark, sf_dir, "documents"), size=4, radius=4)
    return out.select(F.col("id").alias("doc_id"), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), F.col("component").alias("component_id"))


def op5_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0, k=5)


def op6_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = secrets.scanned(table(spark, sf_dir, "documents").select("doc_id", "text"))
    count = lambda k: F.size(F.filter("__spans.base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{secrets.PATTERNS[k].kind}")
    return out.select(F.col("doc_id").cast("long").alias("doc_id"), count(0), count(1), count(2), F.sha2(secrets.shown(F.col("__spans.base")), 256).alias("base_sha256"), secrets.shown(F.col("__spans.all")).alias("spans"))


def op7_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.digests(table(spark, sf_dir, "conversations"))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = token_count.token_counts(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"))
    return out.select(F.col("id").alias("doc_id"), "n_bytes", "n_tokens", (F.col("n_tokens") > 512).alias("over_limit"))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    return mixing.copies(docs.drop("text"), mixing.decisions(docs)).select("row.doc_id", F.col("__domain").alias("domain"), F.col("__lang").alias("lang"), F.col("__source").alias("source"), F.col("__copies").alias("copies"))


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = url_filter.judged(table(spark, sf_dir, "pages"), url_filter.trained(url_filter.LABELLED))
    return out.select(F.col("id").alias("page_id"), "host", "path", "rule", "verdict")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_lm_scoring, op2_quality_rules, op3_sentencepiece, op4_simhash, op5_topk, op6_secrets, op7_chat, op8_token_counts, op9_mixing, op10_url_filter, pipeline)}

ORACLES = {"op2_quality_rules": quality.oracle(), "op7_chat": chat.oracle()}
