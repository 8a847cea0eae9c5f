"""Triangles and degrees of graphs that don't fit a task, against brute force."""

import random
from itertools import combinations

import pytest

from cutloom.operators import decompose, kernel, pieces
from cutloom.operators.graph import Graph
from cutloom.patterns import Pattern, clique, connected_patterns, pseudo_cliques
from cutloom.patterns.algebra import canonical_code
from cutloom.queries import QUERIES


@pytest.mark.parametrize("block, marks", [(1 << 22, 1 << 25), (9, 70)])
def test_triangles_in_pieces(spark, monkeypatch, block, marks):
    draw = random.Random(3)
    edges = [(a * 7 - 50, b * 7 - 50) for a, b in combinations(range(30), 2) if draw.random() < 0.3 or a == 4]
    near = {v: {a + b - v for a, b in edges if v in (a, b)} for e in edges for v in e}
    monkeypatch.setattr(kernel, "MOST_ARCS", 10)
    monkeypatch.setattr(decompose, "clique_rows", lambda *a: pytest.fail("rows of wedges"))
    for name, value in (("BLOCK", block), ("MARKS", marks), ("ROWS", 5)):
        monkeypatch.setattr(pieces, name, value)
    g = Graph(spark.createDataFrame(edges, "src long, dst long"))
    assert {r["v"]: r["deg"] for r in g.degrees().collect()} == {v: len(x) for v, x in near.items()}
    closed = sum(b in near[a] for v in near for a, b in combinations(sorted(near[v]), 2))
    every = sum(len(x) * (len(x) - 1) // 2 for x in near.values())
    assert decompose.clique_count(g, clique(3)).first()["cnt"] == closed // 3
    got = {r["m"]: r["cnt"] for r in decompose.pattern_counts(g, list(connected_patterns(3)), "vertex").collect()}
    assert got == {3: closed // 3, 2: every - closed}


@pytest.mark.parametrize("n, share, small", [(4, 0.4, False), (5, 0.5, True), (6, 0.75, True), (7, 0.85, True), (8, 0.9, False)])
def test_pseudo_cliques_in_pieces(spark, monkeypatch, n, share, small):
    """pseudoclique_7, pseudoclique_8: cliques from each lowest vertex's own triangles, no rows of cliques or of their cuts."""
    draw = random.Random(n)
    edges = [(a * 5 - 20, b * 5 - 20) for a, b in combinations(range(13), 2) if draw.random() < share] + [(70, v) for v in (-20, -15, 0)]
    monkeypatch.setattr(kernel, "MOST_ARCS", 10)
    monkeypatch.setattr(decompose, "clique_rows", lambda *a: pytest.fail("rows of cliques"))
    if small:
        for name, value in (("BLOCK", 20), ("TOGETHER", 2), ("MARKS", 40), ("ROWS", 5), ("GROWN", 4), ("DEALT", 7), ("GROUP", 9)):
            monkeypatch.setattr(pieces, name, value)
    tied, want = {frozenset(e) for e in edges}, {canonical_code(p): 0 for p in pseudo_cliques(n)}
    for s in combinations(sorted({v for e in edges for v in e}), n):
        ties = {(i, j) for i, j in combinations(range(n), 2) if frozenset((s[i], s[j])) in tied}
        if len(ties) >= n * (n - 1) // 2 - 1:
            want[canonical_code(Pattern.of(n, ties))] += 1
    got = {r["pattern"]: r["cnt"] for r in decompose.pseudo_clique_counts(Graph(spark.createDataFrame(edges, "src long, dst long")), n).collect()}
    assert got == {p.name: want[canonical_code(p)] for p in pseudo_cliques(n)} and max(got.values()) > 0


def test_query_in_pieces(spark, monkeypatch):
    """pseudoclique_8"""
    want = QUERIES["pseudoclique_8"](spark, "/root/testdata/sf0.001").collect()
    monkeypatch.setattr(kernel, "MOST_ARCS", 10)
    monkeypatch.setattr(decompose, "clique_rows", lambda *a: pytest.fail("rows of cliques"))
    assert QUERIES["pseudoclique_8"](spark, "/root/testdata/sf0.001").collect() == want
