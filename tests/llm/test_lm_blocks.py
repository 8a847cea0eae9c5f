"""Blocks of the language model: the same scores however rows are dealt, ordered or cut again."""

import collections
import random

import pytest
from pyspark.sql import functions as F

pytest.importorskip("cutloom.llm")
from cutloom.llm import lm_score  # noqa: E402


def _docs(spark):
    rng = random.Random(9)
    texts = [" ".join(rng.choice("abcdefgh") for _ in range(rng.randint(0, 40))) for _ in range(120)]
    return spark.createDataFrame([(i, t, "x", 1) for i, t in enumerate(texts)] + [(3, texts[3], "x", 1)] * 4 + [(None, None, "x", 1)], "doc_id long, text string, block string, docs int")


def test_scores_do_not_depend_on_blocks_or_order(spark):
    docs = _docs(spark)
    want = None
    for parts, block, span in ((1, 12 << 20, 8 << 20), (5, 700, 300), (3, 150, 2000)):
        cut = docs.repartition(parts).sortWithinPartitions(F.rand(parts))
        have = collections.Counter(map(tuple, lm_score.backoff_scores(cut, block_bytes=block, range_bytes=span).collect()))
        want = have if want is None else want
        assert have == want


def test_a_block_is_a_set_of_documents(spark):
    """Re-reading a partition in another order deals the same documents to the same blocks."""
    rows = _docs(spark).select(F.col("doc_id").alias("id"), F.coalesce("text", F.lit("")).alias("text")).coalesce(1)

    def held(df):
        return {r["block"]: sorted(map(str, lm_score.thaw([r["docs"]]).to_pylist())) for r in lm_score.in_blocks(df, 6).collect()}

    assert held(rows) == held(rows.sortWithinPartitions(F.desc("text")))


def test_texts_move_once(spark):
    scores = lm_score.backoff_scores(_docs(spark), block_bytes=700, range_bytes=300)
    scores.collect()
    plan = scores._jdf.queryExecution().executedPlan().toString()
    assert "ReusedExchange" in plan


def test_messages_keep_their_size():
    for size in (10**8, 10**11, 10**14):
        blocks, ranges = lm_score.sized(size, 12 << 20, 8 << 20)
        assert size / 2 / (blocks * ranges) > 0.4 * lm_score.MESSAGE / 2 or blocks * ranges == 1
    assert lm_score.sized(10**9, 12 << 20, 8 << 20) == (80, 120)
