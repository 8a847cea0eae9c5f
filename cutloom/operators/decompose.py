"""Counting by decomposition: part counts are joined on the cut, multiplied, and collisions subtracted.

inj(p), the matchings of p, equals the joint count of a cut (the sum over cut
matches of the product of the parts' counts) less inj of every quotient in
which vertices of different parts coincide.  Quotients are smaller patterns, so
all counts resolve to joint counts and clique enumerations; those terms are
evaluated once each and combined linearly.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from fractions import Fraction
from functools import lru_cache, reduce
from itertools import permutations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from cutloom.operators import kernel, pieces
from cutloom.operators.enumerate import enumerate_matchings
from cutloom.operators.graph import Graph
from cutloom.patterns.algebra import Pattern, automorphisms, canonical_code, restrictions
from cutloom.patterns.catalogue import clique, connected_patterns, pseudo_cliques, spanning_coefficients
from cutloom.plans.cost import DEFAULT, CostModel
from cutloom.plans.cuts import Part, grouped_collisions, part_pattern, parts
from cutloom.plans.search import Plan, best_direct, counting_cut, counting_plan, cut_plan, greedy_order, started_order

WIDE = "decimal(38,0)"


def part_counts(g: Graph, p: Pattern, part: Part, name: str = "cnt", replay: int = 0, limit=None, order: tuple[int, ...] | None = None, as_given: bool = False) -> DataFrame:
    """(m of each cut vertex, count of the part's matchings), enumerated in ``order`` (of the part's vertices, cut first).

    A pendant vertex is the degree and a wedge comes from half its rows, unless
    ``as_given`` asks for the order's own levels.
    """
    q = part_pattern(p, part)
    k = len(part.cut)
    keys = [f"m{i}" for i in range(k)]
    if not as_given and limit is None and k == 1 and q.n == 2 and p.labels is None:
        return g.degrees().select(F.col("v").alias(f"c{part.cut[0]}"), F.col("deg").alias(name))
    if limit is None and q.n > 1 and p.labels is None and g.fits():
        rows = kernel.part_table(g, q, k, tuple(order or greedy_order(q, tuple(range(k)))), name, replay)
    elif not as_given and limit is None and _is_path_from_cut(q, k):
        rows = _eager(g, q, k, name)
    else:
        order = order or greedy_order(q, tuple(range(k)))
        rows = enumerate_matchings(g, q, order, replay=replay, limit=limit).groupBy(*keys).agg(F.count(F.lit(1)).alias(name))
    return rows.select(*[F.col(f"m{i}").alias(f"c{part.cut[i]}") for i in range(k)], name)


def _is_path_from_cut(q: Pattern, k: int) -> bool:
    """Two cut vertices joined by a path of two free ones or fewer, or one with a pendant path: wedge tables do."""
    return k == 2 and q.n == 3 and not q.adjacent(0, 1) and q.adjacent(0, 2) and q.adjacent(1, 2) and q.labels is None


def _eager(g: Graph, q: Pattern, k: int, name: str) -> DataFrame:
    """Common neighbours of two vertices, both orders, from half the wedges."""
    a, b = g.pairs.select(F.col("u").alias("w"), F.col("v").alias("m0")), g.pairs.select(F.col("u").alias("w"), F.col("v").alias("m1"))
    half = a.join(b, "w").where("m0 < m1").groupBy("m0", "m1").agg(F.count(F.lit(1)).alias(name))
    return half.select("m0", "m1", name).unionAll(half.select(F.col("m1").alias("m0"), F.col("m0").alias("m1"), name))


@lru_cache(maxsize=50_000)
def part_key(q: Pattern, k: int) -> tuple[tuple, tuple[int, ...]]:
    """(code, places): parts with one code have the same table, in which cut vertex i of this part is column places[i]."""
    free = (None,) * (q.n - k)
    return min(((canonical_code(q, tuple(map(str, at)) + free), at) for at in permutations(range(k))), key=repr)


class PartTables:
    """The tables of the parts of several counts, each made once; those used more than once are kept until release()."""

    def __init__(self, g: Graph, plans: list[Plan]):
        self.g, self.tables, self.uses = g, {}, Counter(code for plan in plans for code in {part_key(part_pattern(plan.pattern, x), len(x.cut))[0] for x in parts(plan.pattern, plan.cut)})

    def of(self, plan: Plan, i: int, part: Part, name: str) -> DataFrame:
        code, places = part_key(part_pattern(plan.pattern, part), len(part.cut))
        if code not in self.tables:
            order, replay = plan.part_orders[i] if plan.part_orders else None, plan.replays[i] if plan.replays else 0
            rows = part_counts(self.g, plan.pattern, part, "__n", replay, order=order).select(*[F.col(f"c{v}").alias(f"k{at}") for v, at in zip(part.cut, places)], "__n")
            self.tables[code] = rows.persist(StorageLevel.MEMORY_AND_DISK) if self.uses[code] > 1 else rows
        return self.tables[code].select(*[F.col(f"k{at}").alias(f"c{v}") for v, at in zip(part.cut, places)], F.col("__n").alias(name))

    def release(self) -> None:
        for code, rows in self.tables.items():
            if self.uses[code] > 1:
                rows.unpersist()


def joint(g: Graph, p: Pattern, cut: tuple[int, ...], limit_of=None, plan: Plan | None = None, tables: PartTables | None = None) -> DataFrame:
    """One row value: the sum over cut matches of the product of the parts' counts, each part in the plan's order."""
    frames, powers, seen = [], [], {}
    for i, part in enumerate(parts(p, cut)):
        q, name = part_pattern(p, part), f"n{i}"
        key = (canonical_code(q, tuple(str(x) for x in range(len(cut))) + (None,) * len(part.component)), None if limit_of is None else i)
        if key in seen:
            powers[seen[key]] += 1
            continue
        seen[key] = len(frames)
        if tables is not None:
            frames.append(tables.of(plan, i, part, name))
        else:
            own = {} if plan is None or not plan.part_orders else {"order": plan.part_orders[i], "replay": plan.replays[i] if plan.replays else 0}
            frames.append(part_counts(g, p, part, name, limit=None if limit_of is None else limit_of(part), **own))
        powers.append(1)
    keys = [f"c{v}" for v in cut]
    rows = reduce(lambda a, b: a.join(b, keys), frames)
    names = [c for c in rows.columns if c.startswith("n")]
    wide = sum(powers) > 2
    factor = None
    for name, times in zip(names, powers):
        for _ in range(times):
            x = F.col(name).cast(WIDE) if wide else F.col(name)
            factor = x if factor is None else (factor * x).cast(WIDE) if wide else factor * x
    return rows.agg(F.coalesce(F.sum(factor.cast(WIDE)), F.lit(0).cast(WIDE)).cast(WIDE).alias("value"))


@lru_cache(maxsize=4096)
def _representative(code: tuple) -> Pattern:
    n, marks, edges = code
    labels = [m[0] for m in marks]
    return Pattern(n, frozenset(edges), None if all(x == "None" for x in labels) else tuple(labels))


def odd_cycle(p: Pattern) -> bool:
    """Whether a connected pattern's vertices can't be laid out on two sides."""
    side, ready = {0: False}, [0]
    while ready:
        u = ready.pop()
        for v in p.neighbours[u]:
            if v not in side:
                side[v] = not side[u]
                ready.append(v)
    return any(side[a] == side[b] for a, b in p.edges)


class Terms:
    """Linear combinations of joint counts and direct counts, for patterns without labels.

    Each pattern is counted the cheaper way by the model: by a cut, its
    quotients resolved in turn, or directly under restrictions.  A ``two_sided``
    graph holds no pattern with an odd cycle.
    """

    def __init__(self, model: CostModel = DEFAULT, cut_of=None, allow_direct: bool = True, two_sided: bool = False):
        self.model, self.cut_of, self.allow_direct, self.two_sided = model, cut_of, allow_direct, two_sided
        self.known: dict[tuple, dict] = {}
        self.plans: dict[tuple, Plan] = {}

    def plan_of(self, p: Pattern) -> Plan:
        if self.cut_of is not None:
            cut = self.cut_of(p)
            return best_direct(p, self.model) if cut is None else cut_plan(p, tuple(cut), self.model)
        return counting_plan(p, self.model, self.allow_direct)

    def inj(self, p: Pattern) -> dict[tuple, int]:
        code = canonical_code(p)
        if code in self.known:
            return self.known[code]
        p = _representative(code)
        if self.two_sided and odd_cycle(p):
            out: dict[tuple, int] = {}
        elif p.n == 2:
            out = {("edges",): 2}
        elif (plan := self.plan_of(p)).kind == "direct":
            self.plans[term := ("direct", p)] = plan
            out = {term: len(automorphisms(p))}
        else:
            sums: dict[tuple, int] = defaultdict(int)
            self.plans[term := ("joint", p, plan.cut)] = plan
            sums[term] += 1
            for q, times in grouped_collisions(p, plan.cut):
                for t, c in self.inj(q).items():
                    sums[t] -= times * c
            out = {t: c for t, c in sums.items() if c}
        self.known[code] = out
        return out

    def embeddings(self, p: Pattern) -> dict[tuple, Fraction]:
        return {t: Fraction(c, len(automorphisms(p))) for t, c in self.inj(p).items()}


def term_value(g: Graph, term: tuple, plan: Plan | None = None, tables: PartTables | None = None) -> DataFrame:
    """One row value."""
    if term[0] == "edges":
        return g.edges.agg(F.count(F.lit(1)).cast(WIDE).alias("value"))
    if term[0] == "direct":
        return clique_count(g, term[1], plan).select(F.col("cnt").cast(WIDE).alias("value"))
    return joint(g, term[1], term[2], plan=plan, tables=tables)


def kernel_task(g: Graph, term: tuple, plan: Plan | None, model: CostModel) -> kernel.Task | None:
    """A term as a task of the kernel, whose parts all start from the vertex of the cut that makes them cheapest; None if it is left to joins."""
    if term[0] == "edges" or not g.fits():
        return None
    p = term[1]
    if term[0] == "direct":
        if p.is_clique():
            return kernel.walk(p, tuple(range(p.n)), restrictions(p))
        plan = plan or best_direct(p, model)
        return kernel.walk(p, plan.order, plan.pinned or restrictions(p))
    g.lists()
    if g.largest_degree ** (len(term[2]) - 1) > kernel.MOST_MATCHES:
        return None
    pieces = [part_pattern(p, x) for x in parts(p, term[2])]
    orders = [[started_order(q, r, model) for q in pieces] for r in range(len(term[2]))]
    best = min(range(len(orders)), key=lambda r: sum(cost for cost, _ in orders[r]))
    keys = (best, *(v for v in range(len(term[2])) if v != best))
    return tuple(kernel.walk(q, o, keys=keys) for q, (_, o) in zip(pieces, orders[best]))


def planned_task(g: Graph, p: Pattern, plan: Plan) -> kernel.Task | None:
    """A cut as a task of the kernel in the plan's own orders, without replay; None unless all start from one vertex of the cut."""
    starts, k = {o[0] for o in plan.part_orders}, len(plan.cut)
    if not g.fits() or len(starts) > 1 or (start := min(starts)) >= k or g.size == 0:
        return None
    g.lists()
    if g.largest_degree ** (k - 1) > kernel.MOST_MATCHES:
        return None
    keys = (start, *(v for v in range(k) if v != start))
    return tuple(kernel.walk(part_pattern(p, x), o, keys=keys) for x, o in zip(parts(p, plan.cut), plan.part_orders))


def clique_count(g: Graph, p: Pattern, plan: Plan | None = None) -> DataFrame:
    """Cliques (and what is cheaper so) by enumeration; cliques over arcs ordered by degree, so hubs stay light."""
    if not p.is_clique():
        plan = plan or best_direct(p)
        return enumerate_matchings(g, p, plan.order, pinned=plan.pinned or restrictions(p)).agg(F.count(F.lit(1)).alias("cnt"))
    if p.n == 3 and g.size is not None and not g.fits() and (found := pieces.triangles(g)) is not None:
        return g.spark.createDataFrame([(found,)], "cnt long")
    return clique_rows(g, p.n).agg(F.count(F.lit(1)).alias("cnt"))


def clique_rows(g: Graph, n: int) -> DataFrame:
    """(m0 .. m(n-1)): each clique of n vertices once, in the order of degrees."""
    if g.fits():
        p = clique(n)
        return kernel.rows(g, p, tuple(range(n)), restrictions(p))
    arcs = g.with_degree_order()
    rows = arcs.select(F.col("u").alias("m0"), F.col("v").alias("m1"))
    for w in range(2, n):
        rows = rows.join(arcs.select(F.col("u").alias("m0"), F.col("v").alias(f"m{w}")), "m0") if w == 2 else rows.join(arcs.select(F.col("u").alias(f"m{w - 1}"), F.col("v").alias(f"m{w}")), f"m{w - 1}")
        for u in range(1 if w == 2 else 0, w if w == 2 else w - 1):
            rows = rows.join(arcs.select(F.col("u").alias(f"m{u}"), F.col("v").alias(f"m{w}")), [f"m{u}", f"m{w}"], "left_semi")
    return rows


def pseudo_clique_counts(g: Graph, n: int) -> DataFrame:
    """(pattern, n, m, cnt) of the vertex-induced pseudo-cliques that lack at most one edge.

    The cut is the clique of n - 2 vertices, taken once instead of in every
    order; its common neighbours are counted from the cliques of n - 1.  Of the
    pairs of common neighbours those that are adjacent make cliques of n, each
    seen from n(n-1)/2 cuts, and the others the near-cliques.
    """
    full, lacking = sorted(pseudo_cliques(n), key=lambda p: -p.m)
    names = [f"m{i}" for i in range(n - 1)]
    once = F.array(*[F.array(*[x for x in names if x != gone]) for gone in names])
    pairs = F.coalesce(F.sum(F.expr("CAST(c * (c - 1) div 2 AS DECIMAL(38,0))")), F.lit(0)).alias("pairs")
    if g.fits():  # cliques of n are counted as those of n - 1 are made
        rows = kernel.rows(g, clique(n - 1), tuple(range(n - 1)), restrictions(clique(n - 1)), further=kernel.walk(full, tuple(range(n)), restrictions(full)))
        cuts = rows.select("more", F.posexplode(once).alias("i", "cut")).groupBy("cut").agg(F.count(F.lit(1)).alias("c"), F.sum(F.when(F.col("i") == 0, F.col("more")).otherwise(0)).alias("more"))
        both = cuts.agg(F.coalesce(F.sum("more"), F.lit(0)).alias("cnt"), pairs)
    elif g.size is not None and n > 3 and (found := pieces.near_cliques(g, n)) is not None:
        both = g.spark.createDataFrame([found], "cnt long, pairs long")
    else:
        cuts = clique_rows(g, n - 1).select(F.explode(once).alias("cut")).groupBy("cut").agg(F.count(F.lit(1)).alias("c"))
        both = clique_count(g, full).join(F.broadcast(cuts.agg(pairs)))
    row = lambda p, cnt: F.struct(F.lit(p.name).alias("pattern"), F.lit(p.n).alias("n"), F.lit(p.m).alias("m"), cnt.cast("long").alias("cnt"))
    return both.select(F.explode(F.array(row(full, F.col("cnt")), row(lacking, F.col("pairs") - full.m * F.col("cnt")))).alias("x")).select("x.*")


#: Terms beyond this many are evaluated so many at a time, which bounds a plan's size.
CHUNK = 12


def combined(g: Graph, wanted: list[tuple[Pattern, dict[tuple, Fraction]]], names: list[str] | None = None, chunk: int | None = None, plans: dict[tuple, Plan] | None = None) -> DataFrame:
    """(pattern, n, m, cnt): each wanted linear combination of terms.

    The terms' values, one number each, pass through the driver, where they are
    combined exactly; part tables that several terms share are made once.  Terms
    of a graph whose neighbour lists fit a task are counted by the kernel, in one
    job, the others by joins.
    """
    plans = plans or {}
    terms = sorted({t for _, c in wanted for t in c}, key=repr)
    tables = PartTables(g, [plans[t] for t in terms if t in plans and t[0] == "joint"])
    value: dict[tuple, int] = {("edges",): g.size} if g.fits() else {}
    tasks = {t: task for t in terms if (task := kernel_task(g, t, plans.get(t), g.model())) is not None}
    if tasks:
        value |= zip(tasks, kernel.counts(g, list(tasks.values())))
    terms = [t for t in terms if t not in value]
    for i in range(0, len(terms), chunk or CHUNK):
        some = list(enumerate(terms[i: i + (chunk or CHUNK)]))
        frames = [term_value(g, t, plans.get(t), tables if t in plans else None).select(F.lit(k).alias("term"), "value") for k, t in some]
        for r in reduce(DataFrame.unionAll, frames).collect():
            value[some[r["term"]][1]] = int(r["value"])
    tables.release()
    rows = []
    for k, (p, c) in enumerate(wanted):
        count = sum((f * value[t] for t, f in c.items()), Fraction(0))
        if count.denominator != 1:
            raise ArithmeticError(f"{p.name}: matchings aren't a multiple of the automorphisms")
        rows.append((names[k] if names else p.name, p.n, p.m, int(count)))
    return g.spark.createDataFrame(rows, "pattern string, n int, m int, cnt long")


def vertex_coefficients(n: int) -> np.ndarray:
    """Inverse of the spanning coefficients: vertex-induced counts from edge-induced ones, denser patterns solved first."""
    c = spanning_coefficients(n).astype(object)
    k = len(c)
    out = np.zeros((k, k), object)
    for i in range(k - 1, -1, -1):
        out[i, i] = 1
        for j in range(i + 1, k):
            if c[i, j] and i != j:
                out[i] = out[i] - c[i, j] * out[j]
    return out


def wanted_counts(patterns: list[Pattern], induced: str, terms: Terms) -> list[tuple[Pattern, dict[tuple, Fraction]]]:
    if induced == "edge":
        return [(p, terms.embeddings(p)) for p in patterns]
    out = []
    for p in patterns:
        every = connected_patterns(p.n)
        i = [canonical_code(q) for q in every].index(canonical_code(p))
        sums: dict[tuple, Fraction] = defaultdict(Fraction)
        for j, f in enumerate(vertex_coefficients(p.n)[i]):
            if f:
                for t, c in terms.embeddings(every[j]).items():
                    sums[t] += int(f) * c
        out.append((p, {t: c for t, c in sums.items() if c}))
    return out


def pattern_counts(g: Graph, patterns: list[Pattern], induced: str = "edge", model: CostModel | None = None, names: list[str] | None = None, chunk: int | None = None, cut_of=None) -> DataFrame:
    """(pattern, n, m, cnt) of unlabelled patterns; parts and quotients that patterns share are counted once.

    Without a model the graph's own size and density price the plans.
    """
    terms = Terms(model or g.model(), cut_of, two_sided=g.two_sided())
    wanted = wanted_counts(patterns, induced, terms)
    return combined(g, wanted, names, chunk, terms.plans)


def pattern_count(g: Graph, p: Pattern, induced: str = "edge", plan: Plan | None = None, model: CostModel | None = None, via: str = "auto") -> int:
    """Embeddings of a pattern.  ``via`` direct enumerates; indirect decomposes (and solves for vertex-induced counts)."""
    if p.labels is not None:
        return labelled_count(g, p, plan)
    if p.n == 1:
        return g.stats()[0]
    if via == "direct" or (plan is not None and plan.kind == "direct"):
        plan = plan or best_direct(p, model or g.model())
        return enumerate_matchings(g, p, plan.order, induced, plan.pinned or restrictions(p)).count()
    if via == "auto" and induced == "vertex" and plan is None:
        # indirect counts need every denser pattern of the size: the cheaper way is taken
        model = model or g.model()
        denser = [q for q in connected_patterns(p.n) if q.m > p.m]
        direct = best_direct(p, model)
        if direct.cost <= sum(counting_plan(q, model).cost for q in [p, *denser]):
            return enumerate_matchings(g, p, direct.order, induced, direct.pinned or restrictions(p)).count()
    cut_of = None if plan is None else (lambda q: plan.cut if q == p else counting_cut(q, model or DEFAULT))
    return pattern_counts(g, [p], induced, model, cut_of=cut_of).first()["cnt"]


def labelled_count(g: Graph, p: Pattern, plan: Plan | None = None) -> int:
    """A labelled pattern by one cut; quotients with clashing labels don't arise."""
    from cutloom.plans.search import search

    plan = plan or search(p)
    if plan.kind == "direct":
        return enumerate_matchings(g, p, plan.order, pinned=restrictions(p)).count()
    total = joint(g, p, plan.cut).first()["value"]
    for q, times in grouped_collisions(p, plan.cut):
        total -= times * enumerate_matchings(g, q, greedy_order(q)).count()
    whole, rest = divmod(int(total), len(automorphisms(p)))
    assert rest == 0
    return whole


def count_with_cut(g: Graph, p: Pattern, cut: tuple[int, ...], plan: Plan | None = None) -> int:
    """By a given cut, collisions enumerated: for tests and for timing cuts against each other.  ``plan`` gives the orders of parts and collisions."""
    task = kernel_task(g, ("joint", p, cut), plan, g.model()) if plan is None or not plan.part_orders else planned_task(g, p, plan)
    glued = [(q, times, plan.collision_orders[i] if plan is not None and plan.collision_orders else greedy_order(q)) for i, (q, times) in enumerate(grouped_collisions(p, cut))]
    if g.fits():
        found = kernel.counts(g, [*([task] if task else []), *(kernel.walk(q, order) for q, _, order in glued)])
        total = found.pop(0) if task else int(joint(g, p, cut, plan=plan).first()["value"])
    else:
        found = [enumerate_matchings(g, q, order).count() for q, _, order in glued]
        total = int(joint(g, p, cut, plan=plan).first()["value"])
    total -= sum(times * n for (_, times, _), n in zip(glued, found))
    whole, rest = divmod(total, len(automorphisms(p)))
    assert rest == 0
    return whole


def motif_counts(g: Graph, k: int, induced: str = "vertex", chunk: int | None = None, model: CostModel | None = None) -> DataFrame:
    """Counts of all connected patterns of k vertices."""
    return pattern_counts(g, list(connected_patterns(k)), induced, model, chunk=chunk)
