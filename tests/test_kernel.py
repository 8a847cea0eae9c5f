"""The counting kernel against brute force, whatever the sizes of its slices and tables, and the queries that it serves."""

import random
from itertools import combinations

import pytest

from cutloom.operators import decompose, kernel
from cutloom.operators import enumerate as levels
from cutloom.operators.graph import Graph
from cutloom.patterns import Pattern, automorphisms, connected_patterns, cycle, house
from cutloom.patterns.algebra import restrictions
from cutloom.plans.cuts import all_cuts, joinable
from cutloom.plans.search import greedy_order
from cutloom.queries import QUERIES

EDGES = sorted({(a, b) for a, b in combinations(range(3, 20), 2) if random.Random(a * 100 + b).random() < 0.25} | {(1, v) for v in range(3, 17)})
NEAR = {v: {a + b - v for a, b in EDGES if v in (a, b)} for e in EDGES for v in e}


def brute(p, induced="edge"):
    """Matchings, grown vertex by vertex."""
    def grow(m):
        v = len(m)
        if v == p.n:
            return 1
        ok = lambda x: all((m[u] in NEAR[x]) if p.adjacent(u, v) else (induced == "edge" or m[u] not in NEAR[x]) for u in range(v))
        return sum(grow([*m, x]) for x in NEAR if x not in m and ok(x))

    return grow([])


@pytest.fixture(scope="module")
def graph(spark):
    return Graph(spark.createDataFrame(EDGES, "src long, dst long"))


@pytest.fixture
def no_joins(monkeypatch):
    """No term, part or enumeration of matchings may become rows of Spark."""
    def fail(*_, **__):
        raise AssertionError("rows of matchings were joined")

    monkeypatch.setattr(decompose, "term_value", fail)
    monkeypatch.setattr(decompose, "enumerate_matchings", fail)
    monkeypatch.setattr(levels, "extend", fail)
    monkeypatch.setattr(Graph, "with_degree_order", fail)


@pytest.mark.parametrize("rows, cells, wide", [(1 << 19, 1 << 22, 1 << 62), (7, 0, 1 << 62), (7, 0, 0)])
def test_tables_and_totals_by_brute_force(graph, monkeypatch, rows, cells, wide):
    for name, value in (("ROWS", rows), ("CELLS", cells), ("WIDE", wide), ("TOGETHER", 100)):
        monkeypatch.setattr(kernel, name, value)
    lists = kernel.Lists(*graph.lists().value)
    roots = kernel.np.arange(lists.n, dtype=kernel.np.int32)
    for p in (house(), cycle(4), Pattern.parse("01 02 03 14")):
        for induced in ("edge", "vertex"):
            assert sum(kernel.values(lists, [kernel.walk(p, greedy_order(p), restrictions(p), induced)], roots)) * len(automorphisms(p)) == brute(p, induced)
        for cut in all_cuts(p, up_to_symmetry=True):
            if joinable(p, cut):
                value = kernel.values(lists, [decompose.kernel_task(graph, ("joint", p, cut), None, graph.model())], roots)[0]
                assert value - sum(times * brute(q) for q, times in decompose.grouped_collisions(p, cut)) == brute(p)


def test_motifs_of_five_make_no_rows(graph, no_joins):
    """motif5_edge, motif5_vertex, growth_motif_5."""
    for induced in ("edge", "vertex"):
        found = {r["pattern"]: r["cnt"] for r in decompose.motif_counts(graph, 5, induced).collect()}
        assert found == {p.name: brute(p, induced) // len(automorphisms(p)) for p in connected_patterns(5)}


def test_graphs_beyond_the_bound_are_joined(spark, monkeypatch):
    g = Graph(spark.createDataFrame(EDGES, "src long, dst long"))
    monkeypatch.setattr(kernel, "MOST_ARCS", 2 * len(EDGES) - 1)
    monkeypatch.setattr(kernel, "counts", None)
    assert decompose.pattern_count(g, cycle(4)) == brute(cycle(4)) // 8


#: Queries that used to join the rows of every matching.
WITHOUT_ROWS = ["motif5_vertex", "motif5_edge", "growth_motif_5", "cycle5_bip", "cycle6_bip", "model_ablation", "replay_times", "pseudoclique_planted", "pseudoclique_7", "pseudoclique_8"]


@pytest.mark.parametrize("name", WITHOUT_ROWS)
def test_queries_make_no_rows(spark, no_joins, name):
    assert QUERIES[name](spark, "/root/testdata/sf0.001").collect()
