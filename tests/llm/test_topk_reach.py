"""Top-k: first scores, reachable shards and huge components against plain Python."""

import random

import pytest
from pyspark.sql import functions as F

pytest.importorskip("cutloom.llm")
from cutloom.llm import topk  # noqa: E402


def plain(rows, k, every):
    import math

    def whole(x):
        y = max(-(2.0**62), min(2.0**62, 256.0 * x))
        return math.floor(y)

    ints = [(i, [whole(x) for x in v]) for i, v in rows]
    low, high = -(1 << 63) + 1, (1 << 63) - 1
    out = []
    for i, v in ints:
        if i % every == 0:
            best = sorted((-min(high, max(low, sum(a * b for a, b in zip(v, w)))), j) for j, w in ints if j != i)[:k]
            out += [(i, r, j, -s) for r, (s, j) in enumerate(best, 1)]
    return sorted(out)


@pytest.mark.parametrize("longest", [0, 3, 40, 4096])
def test_against_plain(spark, longest):
    rng = random.Random(longest)
    rows = [(i, [rng.gauss(0, 1) * (1 + 9 * (i % 17 == 0)) for _ in range(6)]) for i in range(400)] + [(400, [0.0] * 6), (405, [1e300, -1e300, 0.0, 0.0, 1.0, 2.0]), (410, [1.0, 0.0, 0.0, 0.0, 0.0, 0.0]), (411, [1e17, 1e17, -1e17, 0.5, 0.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(4)
    got = topk.top_k(df, F.col("vec_id") % 5 == 0, 3, block=16, shard=20, longest=longest)
    assert sorted(map(tuple, got.collect())) == plain(rows, 3, 5)


def test_blocks_go_only_where_they_reach(spark):
    """With a few long vectors that answer every query, most pairs of query shard and block never meet."""
    rng = random.Random(1)
    rows = [(i, [abs(rng.gauss(0, 1)) * (100 if i < 20 else 0.01) for _ in range(4)]) for i in range(2000)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(4)
    got = topk.top_k(df, F.col("vec_id") % 50 == 0, 3, block=50, shard=10)
    assert sorted(map(tuple, got.collect())) == plain(rows, 3, 50)


def test_blocks_below_the_known_score_are_skipped():
    import numpy as np

    rng = np.random.default_rng(2)
    far, near = rng.integers(900, 1000, (40, 4)), rng.integers(1, 10, (40, 4))
    ids, q = np.arange(3), rng.integers(1, 10, (3, 4))
    least = np.sort(q @ far.T, axis=1)[:, -2].astype(float)
    assert list(topk.best_of(ids, q, [(np.arange(100, 140), near)], 2, np.eye(4), 2, least)) == []
    kept = list(topk.best_of(ids, q, [(np.arange(100, 140), near), (np.arange(200, 240), far)], 2, np.eye(4), 2, least))
    assert all(v >= 200 for _, _, v, _ in kept) and len(kept) == 6
