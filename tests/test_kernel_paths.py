"""Paths and squares counted by steps from each start, and graphs with two sides, against brute force."""

import random

import numpy as np
import pytest

from cutloom.operators import decompose, kernel
from cutloom.operators.graph import Graph
from cutloom.patterns import automorphisms, cycle
from cutloom.queries import QUERIES

LEFT, RIGHT = range(1, 15), range(101, 108)
TIES = sorted((a, b) for a in LEFT for b in RIGHT if random.Random(a * 1000 + b).random() < 0.5)
OTHERS = sorted((a, b) for a in range(12) for b in range(a + 1, 12) if random.Random(a * 50 + b).random() < 0.4)


def brute(edges, p):
    """Embeddings, grown vertex by vertex."""
    near = {}
    for a, b in edges:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)

    def grow(m):
        v = len(m)
        return 1 if v == p.n else sum(grow([*m, x]) for x in near if x not in m and all(m[u] in near[x] for u in range(v) if p.adjacent(u, v)))

    return grow([]) // len(automorphisms(p))


@pytest.mark.parametrize("edges", [TIES, OTHERS])
@pytest.mark.parametrize("rows", [1 << 19, 3])
def test_tables_of_paths_and_squares(monkeypatch, edges, rows):
    lists = kernel.Lists.of(*np.array(edges).T)
    roots = np.arange(1, lists.n, 2, dtype=np.int32)
    plain = {}
    monkeypatch.setattr(kernel, "ROWS", rows)
    walks = [kernel.Walk(levels, (0, k)) for k, levels in kernel.PATHS.items()] + [kernel.Walk(levels, (0,)) for levels in sorted(kernel.SQUARES)]
    found = [dict(zip(*(x.tolist() for x in kernel.table(lists, w, roots)))) for w in walks]
    monkeypatch.setattr(kernel, "path_edges", lambda w: 0)
    monkeypatch.setattr(kernel, "SQUARES", ())
    for w, got in zip(walks, found):
        keys, counts = kernel.table(lists, w, roots)
        plain = dict(zip(keys.tolist(), counts.tolist()))
        assert got == plain and plain
        assert list(got) == sorted(got)


def test_cycles_of_a_graph_with_two_sides(spark, monkeypatch):
    """cycle5_bip, cycle6_bip: no term has an odd cycle, and paths between the sides are followed from one of them."""
    g = Graph(spark.createDataFrame(TIES, "src long, dst long"))
    assert g.two_sided() and not Graph(spark.createDataFrame(OTHERS, "src long, dst long")).two_sided()
    for k in (4, 6):
        assert decompose.pattern_count(g, cycle(k)) == brute(TIES, cycle(k)) > 0
    monkeypatch.setattr(kernel, "counts", None)
    assert decompose.pattern_count(g, cycle(5)) == 0


def test_no_odd_cycle_is_looked_for(spark, monkeypatch):
    monkeypatch.setattr(kernel, "counts", None)
    assert [r["cnt"] for r in QUERIES["cycle5_bip"](spark, "/root/testdata/sf0.001").collect()] == [0]
