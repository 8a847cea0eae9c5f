"""Larger patterns, plans and measures on a small random graph, against brute force."""

import random
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from cutloom import measure
from cutloom.functions.sql import register_sql
from cutloom.operators import decompose as D
from cutloom.operators.baselines import dfs
from cutloom.operators.enumerate import enumerate_matchings
from cutloom.operators.graph import Graph
from cutloom.operators.profile import profile
from cutloom.patterns import automorphisms, clique, connected_patterns, cycle, house
from cutloom.patterns.algebra import Pattern, canonical_code
from cutloom.plans.search import all_cuts, cut_plan, explain, search

_rng = random.Random(13)
EDGES = [e for e in combinations(range(10), 2) if _rng.random() < 0.42]


@pytest.fixture(scope="module")
def g(spark):
    return Graph(spark.createDataFrame(EDGES, "src long, dst long"))


def brute(p, induced):
    near = {v: set() for v in range(10)}
    for a, b in EDGES:
        near[a].add(b)
        near[b].add(a)
    if induced == "vertex":
        code = canonical_code(p)
        return sum(canonical_code(q) == code for s in combinations(range(10), p.n) if (q := Pattern.of(p.n, [(i, j) for i, j in combinations(range(p.n), 2) if s[j] in near[s[i]]])).m == p.m and q.connected())
    found = 0

    def grow(images):
        nonlocal found
        v = len(images)
        if v == p.n:
            found += 1
            return
        for x in range(10):
            if x not in images and all(images[u] in near[x] for u in p.neighbours[v] if u < v):
                grow([*images, x])

    grow([])
    return found // len(automorphisms(p))


def test_long_cycles(g):
    got = {r["n"]: r["cnt"] for r in D.pattern_counts(g, [cycle(7), cycle(8)]).collect()}
    assert got == {7: brute(cycle(7), "edge"), 8: brute(cycle(8), "edge")}


def test_some_motifs_of_six(g):
    some = [p for p in connected_patterns(6) if p.m >= 11]
    got = {r["pattern"]: r["cnt"] for r in D.pattern_counts(g, some, "vertex").collect()}
    assert got == {p.name: brute(p, "vertex") for p in some}


def test_planted_pseudo_cliques(spark):
    whole = [(i, j) for i, j in combinations(range(9), 2)]
    lacking = [(100 + i, 100 + j) for i, j in combinations(range(7), 2) if (i, j) != (2, 5)]
    got = {r["m"]: r["cnt"] for r in D.pseudo_clique_counts(Graph(spark.createDataFrame(whole + lacking, "src long, dst long")), 7).collect()}
    assert got == {21: 36, 20: 1}


def test_the_priced_orders_run(g):
    """Two orders of a part give different joins, and the same count."""
    p, cut = house(), next(c for c in all_cuts(house()) if len(c) == 2)
    plans = [cut_plan(p, cut, g.model(), orders) for orders in _orders(p, cut)]
    texts = {D.joint(g, p, cut, plan=x)._jdf.queryExecution().optimizedPlan().toString().replace("#", "") for x in plans}
    assert len(texts) == len(plans) >= 2
    assert {D.count_with_cut(g, p, cut, x) for x in plans} == {brute(p, "edge")}


def _orders(p, cut):
    from cutloom.plans.cuts import part_pattern, parts
    from cutloom.plans.search import connected_orders

    each = [connected_orders(part_pattern(p, x)) for x in parts(p, cut)]
    return [[o[0] for o in each], [o[-1] for o in each]]


def test_replayed_parts_and_profiled_plans_count_alike(g):
    cliquelike = [p for p in connected_patterns(5) if 6 <= p.m <= 8]
    want = {p.name: brute(p, "edge") for p in cliquelike}
    assert {r["pattern"]: r["cnt"] for r in D.pattern_counts(g, cliquelike).collect()} == want
    terms = D.Terms(g.model(), allow_direct=False)
    wanted = D.wanted_counts(cliquelike, "edge", terms)
    assert any(any(x.replays) for x in terms.plans.values())
    assert {r["pattern"]: r["cnt"] for r in D.combined(g, wanted, plans=terms.plans).collect()} == want
    again = Graph(g.edges, persist=False)
    profile(again, trials=500)
    assert {r["pattern"]: r["cnt"] for r in D.pattern_counts(again, cliquelike[:3]).collect()} == {p.name: want[p.name] for p in cliquelike[:3]}


def test_replay_makes_fewer_prefix_rows(g):
    """A triangle prefix is enumerated once for six matchings; breaking the whole symmetry makes fewer rows still."""
    plain = enumerate_matchings(g, clique(4)).count()
    again = enumerate_matchings(g, clique(4), (0, 1, 2, 3), replay=3).count()
    broken = D.clique_count(g, clique(4)).first()["cnt"]
    assert plain == again == 24 * broken


def test_measures_and_explain(spark, g):
    slow, bad = measure.run(lambda: 3, 2, limit=-1.0), measure.run(lambda: 1 / 0)
    assert (slow.status, slow.value, bad.status, bad.seconds) == ("late", 3, "failed", None)
    assert measure.speedup(measure.Run(2.0, "ok"), measure.Run(6.0, "ok")) == 3.0 and measure.speedup(bad, slow) is None
    assert "after rewriting" in explain(search(clique(4))) and "cut" in explain(search(cycle(4), g.model(), allow_direct=False))
    register_sql(spark, g, [("cycle", 4)])
    assert spark.sql("SELECT geometric_mean(x) AS m FROM VALUES (2.0D), (8.0D) AS t(x)").first()["m"] == pytest.approx(4.0)
    assert spark.sql("SELECT count(*) AS n, count(DISTINCT m0) AS k FROM triangle_images(1, 2, 3)").first() == (6, 3)
    assert g.degrees().agg(F.count(F.lit(1))).first()[0] == 10


def test_depth_first_beyond_its_bound(g):
    for induced in ("edge", "vertex"):
        assert dfs(g, cycle(4), induced, most_arcs=0).first()["cnt"] == dfs(g, cycle(4), induced).first()["cnt"] > 0
