"""Repeated query rows of the inner product search."""

import pytest
from pyspark.sql import functions as F

pytest.importorskip("cutloom.llm")
from cutloom.llm import topk  # noqa: E402


def test_repeated_query_rows(spark):
    rows = [(i, [float(i % 17), float(i % 5), 1.0]) for i in range(1, 60)] + [(0, [1.0, 2.0, 3.0])] * 3 + [(100, [1.0, 0.0, 0.0]), (100, [0.0, 1.0, 0.0]), (100, [1.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    ints = [(i, tuple(int(256 * x) for x in [*v, 0.0][:3])) for i, v in rows]
    want = []
    for q, v in sorted({(q, v) for q, v in ints if q in (0, 50, 100)}):
        best = sorted((-sum(a * b for a, b in zip(v, w)), j) for j, w in ints if j != q)[:5]
        want += [(q, k + 1, j, -s) for k, (s, j) in enumerate(best)]
    for block in (16, 1024):
        got = topk.top_k(df, F.col("vec_id") % 50 == 0, 5, block=block, shard=2, head=2).collect()
        assert sorted(map(tuple, got)) == sorted(want)
