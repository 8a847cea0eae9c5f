"""Connected sets grown once each, edges by hashed bits, and cliques counted along with smaller ones, against brute force; none by rows of Spark."""

import random
from itertools import combinations

import numpy as np
import pytest

from cutloom.operators import baselines, decompose, kernel
from cutloom.operators.graph import Graph
from cutloom.patterns import Pattern, connected_patterns, pseudo_cliques
from cutloom.patterns.algebra import canonical_code
from cutloom.plans.cuts import all_cuts, joinable
from cutloom.plans.search import cut_plan
from cutloom.queries import ABLATION, QUERIES

EDGES = sorted({(a, b) for a, b in combinations(range(14), 2) if random.Random(a * 100 + b).random() < 0.45} | {(20, v) for v in range(12)})


def brute(k):
    """Vertex-induced counts by code."""
    edges, found = set(EDGES), {}
    for s in combinations(sorted({v for e in EDGES for v in e}), k):
        p = Pattern.of(k, {(i, j) for i, j in combinations(range(k), 2) if (s[i], s[j]) in edges or (s[j], s[i]) in edges})
        if p.connected():
            found[canonical_code(p)] = found.get(canonical_code(p), 0) + 1
    return found


@pytest.fixture(scope="module")
def graph(spark):
    return Graph(spark.createDataFrame(EDGES, "src long, dst long"))


@pytest.fixture
def no_rows(monkeypatch):
    def fail(*_, **__):
        raise AssertionError("rows were joined")

    for owner, name in ((baselines, "_set_shapes"), (baselines, "set_rows"), (decompose, "clique_rows"), (Graph, "adjacency")):
        monkeypatch.setattr(owner, name, fail)


def named(rows):
    return {r["pattern"]: r["cnt"] for r in rows.collect()}


@pytest.mark.parametrize("rows", [1 << 19, 5])
@pytest.mark.parametrize("k", [3, 4, 5])
def test_sets_are_grown_once(monkeypatch, rows, k):
    monkeypatch.setattr(kernel, "ROWS", rows)
    lists, found = kernel.Lists.of(*np.array(EDGES).T), []
    roots = np.arange(lists.n, dtype=np.int32)
    kernel.sets(lists, k, [roots], np.zeros(len(roots), np.int64), found.extend)
    assert len(found) == sum(brute(k).values())


def test_oblivious_counts_make_no_rows(graph, no_rows):
    """baseline_oblivious"""
    want = brute(4)
    assert named(baselines.oblivious(graph, 4)) == {p.name: want.get(canonical_code(p), 0) for p in connected_patterns(4)}


def test_set_enumeration_makes_no_rows(graph, no_rows):
    """inhouse_setenum_5"""
    want = brute(5)
    assert named(baselines.set_enumeration(graph, list(connected_patterns(5)))) == {p.name: want.get(canonical_code(p), 0) for p in connected_patterns(5)}


@pytest.mark.parametrize("n", [4, 5, 6])
def test_pseudo_cliques_in_one_pass(graph, no_rows, monkeypatch, n):
    """pseudoclique_7, pseudoclique_8, pseudoclique_planted"""
    monkeypatch.setattr(decompose, "clique_count", None)
    want = brute(n)
    assert named(decompose.pseudo_clique_counts(graph, n)) == {p.name: want.get(canonical_code(p), 0) for p in pseudo_cliques(n)}


def test_cuts_in_planned_orders_make_no_rows(graph, monkeypatch):
    """model_ablation"""
    monkeypatch.setattr(decompose, "joint", None)
    monkeypatch.setattr(kernel, "part_table", None)
    for p in ABLATION:
        plans = [cut_plan(p, c, graph.model()) for c in all_cuts(p, up_to_symmetry=True) if joinable(p, c)]
        assert {decompose.count_with_cut(graph, p, x.cut, x) for x in plans} == {decompose.pattern_count(graph, p)}


def test_hashed_edges():
    lists = kernel.Lists.of(*np.array(EDGES).T)
    u, v = (x.ravel() for x in np.meshgrid(np.arange(lists.n), np.arange(lists.n)))
    ties = {(lists.ids[a], lists.ids[b]) for a, b in zip(u[lists.tied(u, v)], v[lists.tied(u, v)])}
    assert ties == set(EDGES) | {(b, a) for a, b in EDGES}


def test_large_ids(spark):
    g = Graph(spark.createDataFrame([(a + (1 << 40), b + (1 << 40)) for a, b in EDGES], "src long, dst long"))
    assert named(baselines.oblivious(g, 3)) == {p.name: brute(3)[canonical_code(p)] for p in connected_patterns(3)}


@pytest.mark.parametrize("name", ["baseline_oblivious", "inhouse_setenum_5", "pseudoclique_7"])
def test_queries_make_no_rows(spark, no_rows, name):
    assert QUERIES[name](spark, "/root/testdata/sf0.001").collect()
