"""Counts, fragments, mining and constraints against brute force on small graphs."""

from collections import Counter
from itertools import combinations, permutations

import pytest

from cutloom.operators import baselines, constraints, decompose, fragments, fsm, profile
from cutloom.operators import enumerate as levels
from cutloom.operators.graph import Graph, normalize_edges
from cutloom.patterns import Pattern, automorphisms, chain, clique, connected_patterns, cycle, diamond, house, star, tailed_triangle
from cutloom.plans.cuts import all_cuts, joinable, parts
from cutloom.plans.search import greedy_order

SMALL = [(1, 2), (1, 3), (2, 3), (2, 4), (3, 4), (4, 5), (1, 4), (5, 6), (6, 7), (5, 7), (7, 8), (3, 8), (2, 8), (9, 10), (10, 11), (9, 11), (9, 12)]


@pytest.fixture(scope="module")
def graph(spark):
    rows = [*SMALL, (2, 1), (5, 5), (4, 2)]
    labels = [(v, "ab"[v % 2]) for v in range(1, 13)]
    return Graph(normalize_edges(spark.createDataFrame(rows, "src long, dst long")), spark.createDataFrame(labels, "v long, label string"))


def near():
    out = {}
    for a, b in SMALL:
        out.setdefault(a, set()).add(b)
        out.setdefault(b, set()).add(a)
    return out


def matchings(p, induced="edge"):
    adj, out = near(), []

    def grow(m):
        v = len(m)
        if v == p.n:
            out.append(tuple(m))
            return
        for x in adj:
            if x not in m and all((x in adj[m[u]]) if p.adjacent(u, v) else (induced == "edge" or x not in adj[m[u]]) for u in range(v)):
                grow([*m, x])

    grow([])
    return out


def test_motifs(graph):
    for k in (3, 4):
        for induced in ("edge", "vertex"):
            got = {r["pattern"]: r["cnt"] for r in decompose.motif_counts(graph, k, induced).collect()}
            assert got == {p.name: len(matchings(p, induced)) // len(automorphisms(p)) for p in connected_patterns(k)}


def test_motifs_of_five(graph):
    got = {r["pattern"]: r["cnt"] for r in decompose.motif_counts(graph, 5, "vertex", chunk=10).collect()}
    assert got == {p.name: len(matchings(p, "vertex")) // len(automorphisms(p)) for p in connected_patterns(5)}


def test_every_cut_of_four(graph):
    for p in connected_patterns(4):
        want = len(matchings(p)) // len(automorphisms(p))
        for cut in all_cuts(p, up_to_symmetry=True):
            if joinable(p, cut):
                assert decompose.count_with_cut(graph, p, cut) == want, (p.name, cut)


def test_enumeration_ways(graph):
    for p in (tailed_triangle(), cycle(4), house()):
        for induced in ("edge", "vertex"):
            want = len(matchings(p, induced))
            order = greedy_order(p)
            assert levels.enumerate_matchings(graph, p, order, induced).count() == want
            assert levels.set_rows(graph, p, order, induced).first()["cnt"] == want
            for k in (2, 3):
                assert levels.enumerate_matchings(graph, p, order, induced, replay=k).count() == want
            assert levels.embeddings(graph, p, induced).count() * len(automorphisms(p)) == want


def test_large_patterns_by_decomposition(graph):
    for p in (cycle(6), chain(6)):
        assert decompose.pattern_count(graph, p) == len(matchings(p)) // len(automorphisms(p))


def test_labelled_patterns(graph):
    label = lambda v: "ab"[v % 2]
    for p in (Pattern.of(3, [(0, 1), (0, 2)], "aab"), Pattern.of(4, cycle(4).edges, "abab")):
        want = [m for m in matchings(Pattern(p.n, p.edges)) if all(label(m[v]) == p.labels[v] for v in range(p.n))]
        assert decompose.pattern_count(graph, p) == len(want) // len(automorphisms(p))


@pytest.mark.parametrize(("p", "cut"), [(cycle(4), (0, 2)), (tailed_triangle(), (0,)), (diamond(), (0, 1)), (Pattern.parse("01 02 13"), (0, 1)), (star(3), (0,))])
def test_fragments(graph, p, cut):
    whole = matchings(p)
    rows = fragments.fragments(graph, p, cut).collect()
    for i, part in enumerate(parts(p, cut)):
        want = Counter(tuple(m[v] if v in part.vertices else None for v in range(p.n)) for m in whole)
        got = {tuple(r[f"m{v}"] for v in range(p.n)): r["weight"] for r in rows if r["part"] == i}
        assert got == want and sum(got.values()) == len(whole)


def test_materialize(graph):
    p, cut = cycle(4), (0, 2)
    rows = fragments.fragments(graph, p, cut)
    weights = {(r["part"], r["m0"], r["m1"], r["m2"], r["m3"]): r["weight"] for r in rows.collect()}
    got = Counter((r["part"], r["f0"], r["f1"], r["f2"], r["f3"]) for r in fragments.materialize(graph, p, rows, 2, cut).collect())
    assert got == {k: min(2, w) for k, w in weights.items()}


def test_supports(graph):
    label = lambda v: "ab"[v % 2]
    want = {}
    for name, p in [x for m in fsm.SHAPES.values() for x in m]:
        roles = {}
        for m in matchings(p):
            key = tuple(label(x) for x in m)
            for v in range(p.n):
                roles.setdefault(key, [set() for _ in range(p.n)])[v].add(m[v])
        for key, sets in roles.items():
            if key == min(tuple(key[a[v]] for v in range(p.n)) for a in automorphisms(p)):
                want[name, key] = min(map(len, sets))
    for via in ("fragments", "embeddings"):
        got = {(r["shape"], tuple(x for x in (r["l0"], r["l1"], r["l2"], r["l3"]) if x is not None)): r["support"] for r in fsm.supports(graph, via=via).collect()}
        assert got == want
    frequent = {(r["shape"], r["support"]) for r in fsm.fsm(graph, 3).collect()}
    assert frequent == {(k[0], s) for k, s in want.items() if s >= 3}


def test_generic_support_equals_domains(graph):
    for p in (cycle(4), tailed_triangle()):
        ms = matchings(p)
        assert fragments.support(graph, p).first()["support"] == min(len({m[v] for m in ms}) for v in range(p.n))


def test_constraints(graph):
    p, c, cut = constraints.demo()
    label = lambda v: "ab"[v % 2]
    relaxed = constraints.Constraint((constraints.Sub((0, 1), "differ"), constraints.Sub((1, 3, 4), "equal")))
    for what in (c, relaxed):
        tests = {"differ": lambda ls: len(set(ls)) == len(ls), "equal": lambda ls: len(set(ls)) == 1}
        want = sum(all(tests[s.kind]([label(m[v]) for v in s.vertices]) for s in what.subs) for m in matchings(p))
        assert constraints.constrained_count(graph, p, what, cut).first()["matchings"] == want
        assert constraints.constrained_count(graph, p, what, via="direct").first()["matchings"] == want


def test_baselines(graph):
    want = {p.name: (len(matchings(p)) // len(automorphisms(p)), len(matchings(p, "vertex")) // len(automorphisms(p))) for p in connected_patterns(4)}
    four = list(connected_patterns(4))
    for run, k in ((baselines.set_enumeration, 1), (baselines.symmetry, 1), (baselines.restricted, 1)):
        assert {r["pattern"]: r["cnt"] for r in run(graph, four).collect()} == {p: w[k] for p, w in want.items()}
    for rows in (baselines.restricted_count(graph, four), baselines.native4(graph)):
        assert {r["pattern"]: r["cnt"] for r in rows.collect()} == {p: w[0] for p, w in want.items()}
    assert {r["pattern"]: r["cnt"] for r in baselines.oblivious(graph, 4).collect()} == {p: w[1] for p, w in want.items()}
    for p in (diamond(), tailed_triangle()):
        n = want[next(q.name for q in four if q.m == p.m and sorted(map(len, q.neighbours)) == sorted(map(len, p.neighbours)))][0]
        assert baselines.relational(graph, p).first()["cnt"] == baselines.bfs(graph, p).first()["cnt"] == baselines.dfs(graph, p).first()["cnt"] == baselines.bound_chosen(graph, p) == n
    assert {r["pattern"]: r["cnt"] for r in baselines.shared_pair(graph).collect()} == {q.name: len(matchings(q)) // len(automorphisms(q)) for q in (Pattern.parse("01 02 12 03"), clique(4))}


def test_sampler_is_unbiased(spark):
    edges = [(a, b) for a, b in combinations(range(30), 2) if (a * 7 + b * 3) % 4 == 0]
    g = Graph(spark.createDataFrame(edges, "src long, dst long"))
    some = [chain(3), clique(3), star(3)]
    exact = {p.name: decompose.pattern_count(g, p) for p in some}
    for r in profile.neighbor_sample(g, some, 40_000).collect():
        assert r["approx"] == pytest.approx(exact[r["pattern"]], rel=0.1)


def test_edge_cases(spark):
    empty = Graph(spark.createDataFrame([], "src long, dst long"))
    one = Graph(spark.createDataFrame([(1, 2)], "src long, dst long"))
    hub = Graph(spark.createDataFrame([(0, i) for i in range(1, 13)], "src long, dst long"))
    for p in (clique(3), cycle(4), chain(4)):
        assert decompose.pattern_count(empty, p) == 0 == decompose.pattern_count(one, p)
        assert fragments.fragments(empty, p).count() == 0
    assert decompose.pattern_count(hub, star(4)) == 495 and decompose.pattern_count(hub, chain(4)) == 0
    assert fragments.role_vertices(hub, 10).collect()[0]["v"] == 0


def test_complete_graphs(spark):
    k5 = Graph(spark.createDataFrame(list(combinations(range(5), 2)), "src long, dst long"))
    for p in (clique(4), cycle(5), diamond()):
        assert decompose.pattern_count(k5, p) == len(list(permutations(range(5), p.n))) // len(automorphisms(p))
