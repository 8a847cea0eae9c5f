"""The SimHash step of the near-dedup stage, and few links in few pieces."""

import random

import pytest

pytest.importorskip("cutloom.llm")
pytest.importorskip("corpus_pipeline")
from cutloom.llm import near_copies, simhash  # noqa: E402
from tests.llm.test_near_copies import shingles  # noqa: E402


def test_fingerprints_alone_find_candidates(spark):
    """Without the bands: groups of fingerprints within 4 bits, in them exactly the pairs of similarity 0.8 or more."""
    rng = random.Random(2)
    texts = ["", "one", "one two three four five six"]
    for _ in range(25):
        base = [f"w{rng.randrange(9000)}" for _ in range(300)]
        texts.append(" ".join(base))
        for changes in (1, 2, 4, 20):
            words = list(base)
            for at in rng.sample(range(300), changes):
                words[at] = f"v{rng.randrange(10**6)}"
            texts.append(" ".join(words))
    rows = list(enumerate(texts)) + [(3, texts[3]), (None, texts[5])]
    sets = [shingles(t) for t in texts]
    fps = [simhash.simhash(next(near_copies.shingle_sets(near_copies.pa.array([t]), 5))) for t in texts]

    def closed(pairs):
        up = list(range(len(texts)))

        def root(x):
            while up[x] != x:
                x = up[x]
            return x

        for i, j in pairs:
            x, y = root(i), root(j)
            up[max(x, y)] = min(x, y)
        return [root(i) for i in up]

    every = [(i, j) for i in range(len(texts)) for j in range(i)]
    group = closed((i, j) for i, j in every if (fps[i] ^ fps[j]).bit_count() <= 4)
    want = closed((i, j) for i, j in every if group[i] == group[j] and 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = near_copies.near_copies(docs, candidates=(near_copies.fingerprint_links,)).collect()
    assert {r["id"]: r["component"] for r in got if r["id"] is not None} == dict(enumerate(want))
    assert len(got) == len(rows) and len(set(want)) < len(texts) - 20


def test_few_links_lie_in_few_pieces(spark):
    """However many shuffle partitions there are, and right whatever a piece holds."""
    links = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 101)], "a long, b long")
    want = {**{i: 0 for i in range(1, 61)}, 101: 100}
    found = simhash.components(links)
    assert found.rdd.getNumPartitions() == 1
    assert {r["node"]: r["root"] for r in found.collect()} == want


def test_components_in_several_pieces(spark, monkeypatch):
    monkeypatch.setattr(simhash, "PIECE", 8)
    links = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 101)], "a long, b long")
    assert {r["node"]: r["root"] for r in simhash.components(links).collect()} == {**{i: 0 for i in range(1, 61)}, 101: 100}
