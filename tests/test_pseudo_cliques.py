"""Vertex-induced pseudo-cliques of six to eight vertices against plain enumeration."""

import random
from itertools import combinations

import pytest

from cutloom.operators import decompose
from cutloom.operators.graph import Graph
from cutloom.queries import QUERIES
from cutloom.sources import derive


def counted(edges, n):
    """(cliques, vertex-induced near-cliques): vertex sets lacking no edge, and one."""
    edges = {tuple(sorted(e)) for e in edges}
    vertices = sorted({v for e in edges for v in e})
    adj = {v: sum(1 << i for i, u in enumerate(vertices) if tuple(sorted((u, v))) in edges) for v in vertices}
    near = [adj[v] for v in vertices]
    full = lacking = 0

    def cliques(size, last, common, out):
        if not size:
            out(common)
            return
        x = common >> (last + 1) << (last + 1)
        while x:
            v = (x & -x).bit_length() - 1
            x &= x - 1
            cliques(size - 1, v, common & near[v], out)

    def whole(_):
        nonlocal full
        full += 1

    def ends(common):
        nonlocal lacking
        x = common
        while x:
            v = (x & -x).bit_length() - 1
            x &= x - 1
            lacking += (x & ~near[v]).bit_count()

    every = (1 << len(vertices)) - 1
    cliques(n, -1, every, whole)
    cliques(n - 2, -1, every, ends)
    return full, lacking


def got(df):
    return [r["cnt"] for r in sorted(df.collect(), key=lambda r: -r["m"])]


@pytest.mark.parametrize("n", [4, 6, 7, 8])
def test_random_and_planted(spark, n):
    rng = random.Random(n)
    edges = {e for e in combinations(range(13), 2) if rng.random() < 0.8} | set(combinations(range(20, 29), 2)) - {(20, 21)}
    want = [0, 0]
    for group in combinations(range(29), n):
        m = sum(e in edges for e in combinations(group, 2)) if (max(group) < 13 or min(group) > 19) else 0
        if m >= n * (n - 1) // 2 - 1:
            want[m < n * (n - 1) // 2] += 1
    g = Graph(spark.createDataFrame(sorted(edges), "src long, dst long"))
    assert got(decompose.pseudo_clique_counts(g, n)) == want == list(counted(edges, n)) and min(want) > 0


def test_none(spark):
    g = Graph(spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long"))
    assert got(decompose.pseudo_clique_counts(g, 6)) == [0, 0]


@pytest.mark.parametrize(("n", "kind"), [(6, "bulk"), (7, "all"), (8, "all")])
def test_queries(spark, n, kind):
    edges = [tuple(r) for r in derive.part_edges(spark, "/root/testdata/sf0.001", kind).collect()]
    want = list(counted(edges, n))
    assert got(QUERIES[f"pseudoclique_{n}"](spark, "/root/testdata/sf0.001")) == want
