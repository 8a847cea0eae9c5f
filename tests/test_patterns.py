"""Pattern algebra, planning and the loop program: driver only."""

from itertools import permutations
from math import factorial

import pytest

from cutloom.operators.fragments import StampedTable
from cutloom.patterns import Pattern, automorphisms, canonical_code, chain, clique, connected_patterns, cycle, diamond, house, orbits, pseudo_cliques, restriction_sets, restrictions, spanning_coefficients, star, tailed_triangle
from cutloom.plans import cost, cuts, ir, search


def test_catalogue_sizes():
    assert [len(connected_patterns(n)) for n in range(2, 7)] == [1, 2, 6, 21, 112]
    assert [len(pseudo_cliques(n)) for n in (4, 5, 7, 8)] == [2, 2, 2, 2]


def test_automorphism_orders():
    assert [len(automorphisms(clique(n))) for n in (2, 3, 4, 5)] == [2, 6, 24, 120]
    assert [len(automorphisms(cycle(n))) for n in (4, 5, 6, 7)] == [8, 10, 12, 14]
    assert len(automorphisms(diamond())) == 4 and len(orbits(star(3))) == 2


@pytest.mark.parametrize("n", [3, 4, 5])
def test_restrictions_leave_one_order_of_each_class(n):
    for p in connected_patterns(n):
        for pinned in [restrictions(p), *restriction_sets(p, 6)]:
            kept = sum(all(x[a] < x[b] for a, b in pinned) for x in permutations(range(n)))
            assert kept == factorial(n) // len(automorphisms(p))


def test_codes_survive_relabelling():
    for p in connected_patterns(5):
        for g in list(permutations(range(5)))[::17]:
            assert canonical_code(Pattern.of(5, [(g[a], g[b]) for a, b in p.edges])) == canonical_code(p)


def test_spanning_coefficients():
    three = connected_patterns(3)
    i, j = next(k for k, p in enumerate(three) if p.m == 2), next(k for k, p in enumerate(three) if p.m == 3)
    assert spanning_coefficients(3)[i, j] == 3


def test_cut_counts():
    assert [len(cuts.all_cuts(p)) for p in (chain(3), star(3), chain(4), tailed_triangle(), cycle(4), diamond())] == [1, 4, 5, 3, 2, 1]
    assert sum(len(cuts.all_cuts(p)) for p in connected_patterns(5)) == 160
    assert all(not cuts.all_cuts(clique(n)) for n in (3, 4, 5))


def test_collisions_of_the_four_cycle():
    found = cuts.collisions(cycle(4), (0, 2))
    assert len(found) == 1 and canonical_code(found[0].quotient) == canonical_code(chain(3))


def test_labels_stop_collisions():
    p = Pattern.of(3, [(0, 1), (0, 2)], ["x", "a", "b"])
    assert not cuts.collisions(p, (0,)) and len(cuts.collisions(Pattern.of(3, p.edges, ["x", "a", "a"]), (0,))) == 1


def test_every_pattern_but_cliques_has_a_usable_cut():
    for n in (3, 4, 5, 6):
        assert all((search.counting_cut(p) is None) == p.is_clique() for p in connected_patterns(n))


def test_uniform_model_example():
    assert cost.UniformModel(4.8e6, p=1.8e-6).matchings(clique(4)) == pytest.approx(1.9e-8, rel=0.1)


def test_local_model_closes_wedges():
    n, degree = 4.8e6, 18.0
    m = cost.LocalModel(n, degree, 0.27)
    assert m.matchings(clique(3)) == pytest.approx(n * degree * degree * 0.27, rel=1e-6)


def test_search_prefers_a_cut_where_parts_are_small():
    plan = search.search(chain(5), cost.UniformModel(1e6, 50))
    assert plan.kind == "cut" and "cut" in search.explain(plan)
    assert search.search(clique(4)).kind == "direct"
    assert search.bound_choice(cycle(4)) is not None


def test_replay_choice():
    order = search.greedy_order(clique(3))
    assert (3, 6) in search.replayable(house(), (0, 1, 2)) or search.replayable(clique(4), (0, 1, 2, 3))[-1] == (3, 6)
    assert search.best_replay(clique(3), order) >= 2


def test_program_rewrites():
    p = clique(4)
    root = ir.program(p, [0, 1, 2, 3], restrictions(p))
    small = ir.dedupe(root)
    assert ir.set_operations(small) < ir.set_operations(root)
    moved = ir.hoist(small)
    assert ir.set_operations(moved) <= ir.set_operations(small) and "for v3" in ir.shown(moved)
    assert "replay x6" in ir.shown(ir.replayed(root, 3, 6))


def test_stamped_table_wraps():
    t = StampedTable(bits=2)
    for _ in range(9):
        t.add("k")
        assert t.get("k") == 1
        t.clear()
        assert t.get("k") == 0
