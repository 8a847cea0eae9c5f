"""Supports from neighbour lists against those of whole matchings."""

import random

import pytest

from cutloom.operators import fsm, labelled
from cutloom.operators.graph import Graph


def labelled_graph(spark, seed, n, share, kinds):
    draw = random.Random(seed)
    edges = [(a, b) for a in range(n) for b in range(a + 1, n) if draw.random() < share]
    names = [(v, None if draw.random() < 0.1 else "xyzuvw"[draw.randrange(kinds)]) for v in range(n) if draw.random() < 0.95]
    return Graph(spark.createDataFrame(edges, "src long, dst long"), spark.createDataFrame(names, "v long, label string"))


@pytest.mark.parametrize("seed, n, share, kinds", [(1, 14, 0.2, 2), (2, 24, 0.12, 3), (3, 12, 0.7, 2), (4, 30, 0.08, 2), (5, 16, 0.3, 1)])
def test_supports_equal_those_of_matchings(spark, monkeypatch, seed, n, share, kinds):
    g = labelled_graph(spark, seed, n, share, kinds)
    want = {at_least: sorted(map(str, fsm.supports(g, 3, "embeddings", at_least).collect())) for at_least in (None, 4)}
    monkeypatch.setattr(fsm, "_arcs", lambda *a: pytest.fail("rows of labelled arcs"))
    monkeypatch.setattr(labelled, "ROWS", 7)
    monkeypatch.setattr(labelled, "TOGETHER", 50)
    for at_least, rows in want.items():
        for via in ("fragments", "auto"):
            assert sorted(map(str, fsm.supports(g, 3, via, at_least).collect())) == rows
    assert len(fsm.supports(g, 1).collect()) == sum("shape='edge'" in x for x in want[None])


def test_many_labels_are_joined(spark):
    g = Graph(spark.createDataFrame([(1, 2), (2, 3), (3, 40)], "src long, dst long"), spark.createDataFrame([(v, str(v)) for v in range(1, 41)], "v long, label string"))
    assert labelled.supports(g, 3, None) is None
    assert {r["shape"] for r in fsm.supports(g).collect()} == {"edge", "chain3", "chain4"}
