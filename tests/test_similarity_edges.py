"""The similarity join against all pairs, with vectors that have no cosine, of several lengths, and repeated ids."""

import math

import numpy as np

from cutloom.sources import derive


def test_similar_pairs_and_odd_vectors(spark, monkeypatch):
    monkeypatch.setattr(derive, "SLICE", 7)
    rng = np.random.default_rng(3)
    rows = [(i, [float(x) for x in rng.normal(size=6)]) for i in range(120)]
    rows += [(200, [0.0] * 6), (201, None), (202, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (203, []), (204, [1.0, 2.0]), (205, [2.0, 3.9]), (5, rows[9][1]), (7, rows[7][1]), (None, rows[3][1])]
    cosine = lambda a, b: sum(x * y for x, y in zip(a, b)) / math.sqrt(sum(x * x for x in a) * sum(y * y for y in b))
    good = [(i, [float(np.float32(x)) for x in v]) for i, v in rows if i is not None and v and None not in v and any(v)]
    want = {(min(i, j), max(i, j)) for i, v in good for j, w in good if i != j and len(v) == len(w) and cosine(v, w) >= 0.3}
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    for blocks in (1, 8, 40):
        got = [tuple(r) for r in derive.similarity_edges(df, 0.3, blocks).collect()]
        assert len(got) == len(set(got)) and set(got) == want
    assert derive.similarity_edges(df.limit(0)).count() == 0
