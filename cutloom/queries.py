"""The workloads on the given tables, by name; each takes (spark, sf_dir)."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutloom import measure
from cutloom.operators import baselines as B
from cutloom.operators import constraints as C
from cutloom.operators import decompose as D
from cutloom.operators import enumerate as E
from cutloom.operators import fragments as R
from cutloom.operators import fsm as M
from cutloom.operators import profile as P
from cutloom.operators.graph import Graph
from cutloom.patterns import Pattern, automorphisms, chain, clique, connected_patterns, cycle, diamond, house, pseudo_cliques, tailed_triangle
from cutloom.patterns.algebra import restrictions
from cutloom.plans.cost import LocalModel, UniformModel
from cutloom.plans.cuts import joinable, part_pattern, parts
from cutloom.plans.search import all_cuts, best_replay, counting_cut, cut_plan, greedy_order, random_plans, search
from cutloom.sources import derive as S

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def query(fn=None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        return f

    return add(fn) if fn else add


def _counts(name: str, patterns, kind: str, induced: str = "edge", chunk: int | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = graph(spark, sf_dir, kind)
        return D.pattern_counts(g, list(patterns), induced, chunk=chunk)

    QUERIES[name] = run


def graph(spark: SparkSession, sf_dir: str, kind: str, label: str | None = None) -> Graph:
    if kind == "bip":
        return S.bipartite_graph(spark, sf_dir)
    if kind == "sim":
        return S.similarity_graph(spark, sf_dir)
    if kind == "act":
        return S.activity_graph(spark, sf_dir)
    return S.part_graph(spark, sf_dir, kind, label)


# --- counts (name: patterns, graph, induced) ----------------------------------

COUNTS: dict[str, tuple[tuple[Pattern, ...], str, str]] = {
    "cycle4": ((cycle(4),), "bulk", "edge"),
    "triangle_count": ((clique(3),), "bulk", "edge"), "triangle_count_ret": ((clique(3),), "ret", "edge"), "triangle_count_bip": ((clique(3),), "bip", "edge"), "triangle_count_sim": ((clique(3),), "sim", "edge"),
    "motif3_edge": (connected_patterns(3), "bulk", "edge"), "motif3_vertex": (connected_patterns(3), "bulk", "vertex"), "motif3_vertex_ret": (connected_patterns(3), "ret", "vertex"), "motif3_vertex_all": (connected_patterns(3), "all", "vertex"),
    "motif4_edge": (connected_patterns(4), "bulk", "edge"), "motif4_vertex": (connected_patterns(4), "bulk", "vertex"), "motif4_vertex_ret": (connected_patterns(4), "ret", "vertex"),
    "motif5_edge": (connected_patterns(5), "bulk", "edge"), "motif5_vertex": (connected_patterns(5), "bulk", "vertex"),
    "pseudoclique_4": (pseudo_cliques(4), "bulk", "vertex"), "pseudoclique_5": (pseudo_cliques(5), "bulk", "vertex"), "pseudoclique_6": (pseudo_cliques(6), "bulk", "vertex"),
    "cycle5": ((cycle(5),), "bulk", "edge"), "cycle6": ((cycle(6),), "bulk", "edge"), "cycle4_bip": ((cycle(4),), "bip", "edge"), "cycle5_bip": ((cycle(5),), "bip", "edge"),
    "chain5_count": ((chain(5),), "bulk", "edge"), "clique4": ((clique(4),), "bulk", "edge"), "clique5": ((clique(5),), "bulk", "edge"), "house_count": ((house(),), "bulk", "edge"),
    "growth_motif_3": (connected_patterns(3), "bulk", "vertex"), "growth_motif_4": (connected_patterns(4), "bulk", "vertex"), "growth_motif_5": (connected_patterns(5), "bulk", "vertex"),
    "growth_cycle_3": ((cycle(3),), "bulk", "edge"), "growth_cycle_4": ((cycle(4),), "bulk", "edge"), "growth_cycle_5": ((cycle(5),), "bulk", "edge"), "growth_cycle_6": ((cycle(6),), "bulk", "edge"),
}
for _name, (_patterns, _kind, _induced) in COUNTS.items():
    _counts(_name, _patterns, _kind, _induced, 12 if len(_patterns) > 10 else None)

#: Larger patterns: brute force is too slow in SQL; tests/test_large.py holds such counts against brute force on a small random graph.
LARGE = {"motif6_vertex": (connected_patterns(6), "bulk45", "vertex", 12), "cycle7": ((cycle(7),), "bulk45", "edge", None), "cycle8": ((cycle(8),), "bulk45", "edge", None), "cycle6_bip": ((cycle(6),), "bip", "edge", None), "growth_motif_6": (connected_patterns(6), "bulk45", "vertex", 12)}
for _name, (_patterns, _kind, _induced, _chunk) in LARGE.items():
    _counts(_name, _patterns, _kind, _induced, _chunk)

#: Vertex-induced, on the graphs that hold some: 7 and 8 on all lines.
for _n, _kind in ((6, "bulk"), (7, "all"), (8, "all")):
    QUERIES[f"pseudoclique_{_n}"] = lambda spark, sf_dir, n=_n, kind=_kind: D.pseudo_clique_counts(graph(spark, sf_dir, kind), n)


# --- baselines ----------------------------------------------------------------

BASELINES: dict[str, tuple[tuple[Pattern, ...], str, str]] = {}


def _baseline(name: str, patterns, kind: str, induced: str, run: Callable[[Graph], DataFrame]) -> None:
    BASELINES[name] = (tuple(patterns), kind, induced)
    QUERIES[name] = lambda spark, sf_dir: run(graph(spark, sf_dir, kind))


_four, _three = connected_patterns(4), connected_patterns(3)
_baseline("inhouse_setenum_3", _three, "ret", "vertex", lambda g: B.set_enumeration(g, list(_three)))
_baseline("inhouse_setenum_4", _four, "bulk", "vertex", lambda g: B.set_enumeration(g, list(_four)))
_baseline("inhouse_setenum_5", connected_patterns(5), "bulk", "vertex", lambda g: B.set_enumeration(g, list(connected_patterns(5))))
_baseline("baseline_setenum", _four, "bulk", "vertex", lambda g: B.set_enumeration(g, list(_four)))
_baseline("baseline_symmetry", _four, "bulk", "vertex", lambda g: B.symmetry(g, list(_four)))
_baseline("baseline_restr", _four, "bulk", "vertex", lambda g: B.restricted(g, list(_four)))
_baseline("baseline_restr_count", _four, "bulk", "edge", lambda g: B.restricted_count(g, list(_four)))
_baseline("baseline_oblivious", _four, "bulk", "vertex", lambda g: B.oblivious(g, 4))
_baseline("baseline_join", (diamond(),), "bulk", "edge", lambda g: B.relational(g, diamond()))
_baseline("baseline_bfs", (tailed_triangle(),), "bulk", "edge", lambda g: B.bfs(g, tailed_triangle()))
_baseline("baseline_dfs", (cycle(4),), "bulk", "edge", lambda g: B.dfs(g, cycle(4)))
_baseline("baseline_native45", _four, "bulk", "edge", B.native4)
_baseline("shared_prefix_pair", (tailed_triangle(), clique(4)), "bulk", "edge", B.shared_pair)


@query
def baseline_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 4-cycle and the house by the cut of the smallest bound."""
    g = graph(spark, sf_dir, "bulk")
    rows = [(p.name, p.n, p.m, B.bound_chosen(g, p)) for p in (cycle(4), house())]
    return spark.createDataFrame(rows, "pattern string, n int, m int, cnt long")


BASELINES["baseline_bound"] = ((cycle(4), house()), "bulk", "edge")


@query
def baseline_perfect(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = graph(spark, sf_dir, "bulk45")
    rows = [(p.name, p.n, p.m, B.perfect(g, p)[2]) for p in (tailed_triangle(),)]
    return spark.createDataFrame(rows, "pattern string, n int, m int, cnt long")


BASELINES["baseline_perfect"] = ((tailed_triangle(),), "bulk45", "edge")


# --- fragments ----------------------------------------------------------------

FRAGMENTS = {"fragments_cycle4": (cycle(4), (0, 2)), "fragments_chain4": (Pattern.parse("01 02 13"), (0, 1)), "fragments_tailed_triangle": (tailed_triangle(), (0,)), "fragments_diamond": (diamond(), (0, 1))}
for _name, (_p, _cut) in FRAGMENTS.items():
    QUERIES[_name] = lambda spark, sf_dir, p=_p, cut=_cut: R.fragments(graph(spark, sf_dir, "bulk"), p, cut)


@query
def materialize_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Up to two whole 4-cycles for each fragment: by part, how many fragments and how many matchings."""
    g = graph(spark, sf_dir, "bulk")
    whole = R.materialize(g, cycle(4), R.fragments(g, cycle(4), (0, 2)), 2, (0, 2))
    return whole.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.sum("m1").alias("sum_m1"), F.sum("m3").alias("sum_m3"))


# --- mining, stars, constraints -------------------------------------------------

def _fsm(name: str, kind: str, label: str, threshold: int, via: str) -> None:
    QUERIES[name] = lambda spark, sf_dir: M.fsm(graph(spark, sf_dir, kind, label), threshold, via=via)


for _t in (50, 100, 150):
    _fsm(f"fsm_t{_t}", "bulk", "p_type", _t, "auto")
_fsm("fsm_t100_embeddings", "bulk", "p_type", 100, "embeddings")
_fsm("fsm_t100_fragments", "bulk", "p_type", 100, "fragments")
_fsm("fsm_sim_t10", "sim", "label", 10, "auto")


@query
def fsm_synthetic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return M.fsm(S.synthetic_labels(graph(spark, sf_dir, "bulk"), 8), 50)


SWEEP = (10, 20, 50, 75, 100, 125, 150, 175, 200)


@query
def fsm_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    return M.fsm_sweep(graph(spark, sf_dir, "bulk", "p_type"), list(SWEEP))


@query
def star10_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels of the centres of stars of ten leaves, and how many centres there are."""
    g = graph(spark, sf_dir, "bulk", "p_type")
    return R.role_vertices(g, 10).join(g.vertices, "v").groupBy("label").agg(F.count(F.lit(1)).alias("n"))


@query
def constraint_demo(spark: SparkSession, sf_dir: str) -> DataFrame:
    p, c, cut = C.demo()
    return C.constrained_count(graph(spark, sf_dir, "bulk", "p_type"), p, c, cut)


@query
def constraint_differ(spark: SparkSession, sf_dir: str) -> DataFrame:
    p, c, cut = C.demo()
    return C.constrained_count(graph(spark, sf_dir, "bulk", "p_type"), p, C.Constraint(c.subs[:1]), cut)


# --- identities, replay, models ---------------------------------------------------

@query
def edge_to_vertex_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertex-induced 3-chains directly, and as edge-induced ones less three times the triangles."""
    g = graph(spark, sf_dir, "bulk")
    p = Pattern.parse("01 02")
    direct = E.direct_count(g, p, "vertex").select(F.col("cnt").alias("direct"))
    chains = E.direct_count(g, p).select(F.col("cnt").alias("chains"))
    triangles = E.direct_count(g, clique(3)).select(F.col("cnt").alias("triangles"))
    return direct.join(F.broadcast(chains)).join(F.broadcast(triangles)).select("direct", (F.col("chains") - 3 * F.col("triangles")).alias("indirect"))


@query
def replay_on_off(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Matchings of the 20 patterns of five vertices that aren't cliques, with and without replay of a symmetric prefix."""
    g = graph(spark, sf_dir, "bulk")
    out = []
    for p in connected_patterns(5):
        if p.is_clique():
            continue
        order = greedy_order(p)
        k = max(best_replay(p, order), 2)
        plain = E.enumerate_matchings(g, p, order).agg(F.count(F.lit(1)).alias("plain"))
        again = E.enumerate_matchings(g, p, order, replay=k).agg(F.count(F.lit(1)).alias("replayed"))
        out.append(plain.join(F.broadcast(again)).select(F.lit(p.name).alias("pattern"), F.expr(f"plain div {len(automorphisms(p))}").alias("plain"), F.expr(f"replayed div {len(automorphisms(p))}").alias("replayed")))
    return reduce(DataFrame.unionAll, out)


@query
def replay_times(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of the same enumerations, the ratio, and those of whole symmetry breaking, which beats replay where the whole pattern is symmetric."""
    g = graph(spark, sf_dir, "bulk")
    model, rows = g.model(), []
    for p in connected_patterns(5):
        if p.is_clique():
            continue
        order = greedy_order(p)
        k = max(best_replay(p, order, model), 2)
        plain, again, broken = (measure.run(lambda p=p, order=order, own=own: E.count_matchings(g, p, order, **own), 1) for own in ({}, {"replay": k}, {"pinned": restrictions(p)}))
        rows.append((p.name, len(automorphisms(p)), k, plain.seconds, again.seconds, measure.speedup(again, plain), broken.seconds, broken.value * len(automorphisms(p)) == again.value))
    return spark.createDataFrame(rows, "pattern string, automorphisms int, prefix int, plain_s double, replayed_s double, speedup double, restricted_s double, equal boolean")


@query
def profiled_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts whose plans are priced by the graph's own profile."""
    g = graph(spark, sf_dir, "bulk")
    P.profile(g, trials=20_000)
    return D.pattern_counts(g, [house(), cycle(5), chain(5), diamond()])


@query
def profiling_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of the profile of patterns up to four vertices, beside the motif count it serves."""
    g = graph(spark, sf_dir, "bulk")
    profiling = measure.run(lambda: P.profile(g, trials=20_000), 1)
    counting = measure.run(lambda: D.motif_counts(g, 4).collect(), 1)
    return spark.createDataFrame([("bulk", g.size, profiling.seconds, counting.seconds)], "graph string, edges long, profile_s double, motif4_s double")


@query
def speedups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean seconds of three runs of the 4-motif count, ours and each baseline's, how many times longer each takes, and its status."""
    g = graph(spark, sf_dir, "bulk")
    four = list(_four)
    ours = measure.run(lambda: D.motif_counts(g, 4).collect(), 3)
    others = {"set enumeration": lambda: B.set_enumeration(g, four), "symmetry": lambda: B.symmetry(g, four), "restrictions": lambda: B.restricted(g, four), "oblivious": lambda: B.oblivious(g, 4)}
    rows = [("decomposition", ours.seconds, 1.0, ours.status)]
    for name, make in others.items():
        other = measure.run(lambda make=make: make().collect(), 3, LIMIT_S)
        rows.append((name, other.seconds, measure.speedup(ours, other), other.status))
    return spark.createDataFrame(rows, "engine string, seconds double, times_longer double, status string")


#: Seconds after which a baseline counts as late, so it isn't repeated.
LIMIT_S = 300.0


def model_rows(g: Graph, patterns: tuple[Pattern, ...], k: int, seed: int = 1, times: measure.PieceTimes | None = None) -> list[tuple[float, float, float, float]]:
    """(seconds, uniform, local, profiled estimate) of random plans of an application: one random plan of each pattern, summed.

    A plan's parts and collisions run in the very orders that are priced.
    """
    from cutloom.plans.cost import cut_cost

    n, m = g.stats()
    degree = 2 * m / n
    models = [UniformModel(n, degree), LocalModel(n, degree, P.local_probability(g)), P.ProfileStore(g, trials=20_000).model(4)]
    times = times or measure.PieceTimes(g)
    out, drawn = [], [random_plans(p, k, seed + i) for i, p in enumerate(patterns)]
    times.run([plan for plans in drawn for plan in plans])
    for plans in zip(*drawn):
        seconds = sum(times.plan(plan) for plan in plans)
        out.append((seconds, *[sum(cut_cost(plan.pattern, plan.cut, [list(o) for o in plan.part_orders], x, collision_orders=plan.collision_orders) for plan in plans) for x in models]))
    return out


#: The 5-motifs that have a cut, the ladder of six vertices and the 6-cycle with a chord.
APPLICATIONS = {"motif5": tuple(p for p in connected_patterns(5) if not p.is_clique()), "ladder6": (Pattern.parse("01 12 34 45 03 14 25"),), "chord6": (Pattern.parse("01 12 23 34 45 05 02"),)}
PLANS = 100


def correlations(g: Graph, applications: dict[str, tuple[Pattern, ...]], k: int) -> DataFrame:
    times = measure.PieceTimes(g)
    rows = [(name, *map(float, r)) for name, patterns in applications.items() for r in model_rows(g, patterns, k, times=times)]
    df = g.spark.createDataFrame(rows, "application string, seconds double, uniform double, local double, profiled double")
    return df.groupBy("application").agg(F.corr("seconds", "uniform").alias("uniform"), F.corr("seconds", "local").alias("local"), F.corr("seconds", "profiled").alias("profiled"), F.count(F.lit(1)).alias("n"))


@query
def model_correlation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Correlation of each model's estimate with the run time over PLANS random plans of each application."""
    return correlations(graph(spark, sf_dir, "bulk"), APPLICATIONS, PLANS)


ABLATION = (house(), Pattern.parse("01 02 03 12 13 24"), Pattern.parse("01 02 03 14 24"))


@query
def model_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cut that each model picks for three patterns, its count and its seconds; perfect: every cut is run and the fastest kept."""
    g = graph(spark, sf_dir, "bulk")
    n, m = g.stats()
    degree = 2 * m / n
    models = {"uniform": UniformModel(n, degree), "local": LocalModel(n, degree, P.local_probability(g)), "profiled": P.ProfileStore(g, trials=20_000).model(4)}
    rows = []
    for p in ABLATION:
        known: dict[tuple, measure.Run] = {}

        def timed(plan, p=p, known=known) -> measure.Run:
            key = (plan.cut, plan.part_orders)
            if key not in known:
                known[key] = measure.run(lambda: D.count_with_cut(g, p, plan.cut, plan), 1)
            return known[key]

        for name, model in models.items():
            plan = search(p, model, allow_direct=False)
            rows.append((p.name, name, ",".join(map(str, plan.cut)), timed(plan).value, timed(plan).seconds))
        every = [cut_plan(p, c, models["uniform"]) for c in all_cuts(p, up_to_symmetry=True) if joinable(p, c)]
        for plan in every:
            timed(plan)
        best = min(known, key=lambda k: known[k].seconds)
        rows.append((p.name, "perfect", ",".join(map(str, best[0])), known[best].value, known[best].seconds))
    return spark.createDataFrame(rows, "pattern string, model string, cut string, cnt long, seconds double")


@query
def cut_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the parts of every cut of the house and seconds of its count: the worst against the best."""
    g = graph(spark, sf_dir, "bulk")
    p = house()
    out = []
    for cut in all_cuts(p, up_to_symmetry=True):
        if joinable(p, cut):
            rows = sum(E.count_matchings(g, part_pattern(p, x)) for x in parts(p, cut))
            took = measure.run(lambda cut=cut: D.count_with_cut(g, p, cut), 1)
            out.append((",".join(map(str, cut)), rows, took.value, took.seconds))
    return spark.createDataFrame(out, "cut string, rows long, cnt long, seconds double")


@query
def profile_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sampled against exact counts of the patterns of three to five vertices, and the relative error."""
    g = graph(spark, sf_dir, "bulk")
    some = [p for n in (3, 4, 5) for p in connected_patterns(n)]
    exact = D.pattern_counts(g, some).select("pattern", F.col("cnt").alias("exact"))
    found = P.neighbor_sample(g, some, 100_000).join(exact, "pattern")
    return found.withColumn("error", F.when(F.col("exact") > 0, F.abs(F.col("approx") - F.col("exact")) / F.col("exact")))


@query
def estimated_loops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of each level of a house enumeration, estimated by the uniform model and observed."""
    g = graph(spark, sf_dir, "bulk")
    n, m = g.stats()
    order = greedy_order(house())
    estimate = UniformModel(n, 2 * m / n).loop_sizes(house(), list(order))
    seen = [E.enumerate_matchings(g, house().induced(list(order[:k]))).agg(F.count(F.lit(1)).alias("observed")).select(F.lit(k).alias("level"), F.lit(float(estimate[k - 1])).alias("estimated"), "observed") for k in range(2, 6)]
    return reduce(DataFrame.unionAll, seen)


@query
def compile_vs_exec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds to plan and to run motif counts of three to six vertices (six on the thinner graph)."""
    rows = []
    for k, kind in ((3, "bulk"), (4, "bulk"), (5, "bulk"), (6, "bulk45")):
        g = graph(spark, sf_dir, kind)
        terms = D.Terms(g.model())
        planned = measure.run(lambda k=k, terms=terms: D.wanted_counts(list(connected_patterns(k)), "vertex", terms), 1)
        ran = measure.run(lambda g=g, planned=planned, terms=terms: D.combined(g, planned.value, plans=terms.plans).collect(), 1)
        rows.append((k, kind, planned.seconds, ran.seconds))
    return spark.createDataFrame(rows, "k int, graph string, plan_s double, run_s double")


@query
def fragments_vs_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many rows the parts of the planner's cut have, against the embeddings they count."""
    g = graph(spark, sf_dir, "bulk")
    out = []
    for p in (cycle(4), chain(5), house()):
        cut = counting_cut(p)
        rows = reduce(DataFrame.unionAll, [R.part_rows(g, p, x).agg(F.count(F.lit(1)).alias("r")) for x in parts(p, cut)]).agg(F.sum("r").alias("fragments"))
        out.append(rows.join(F.broadcast(D.pattern_counts(g, [p]))).select("pattern", "fragments", "cnt"))
    return reduce(DataFrame.unionAll, out)


@query
def rmat_4motif(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Motifs of four vertices of a generated graph that grows with the tables: the next power of two above the number of parts, four edges a vertex."""
    scale = max(4, (S.table(spark, sf_dir, "part").count() - 1).bit_length())
    return D.motif_counts(Graph(S.rmat_edges(spark, scale, 4)), 4)


@query
def pseudoclique_planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pseudo-cliques of seven vertices on the bulk graph with a planted clique of nine and a near-clique of eight, on vertices of their own."""
    edges = S.part_edges(spark, sf_dir, "bulk")
    planted = [(-i, -j) for i in range(1, 10) for j in range(1, i)] + [(-100 - i, -100 - j) for i in range(1, 9) for j in range(1, i) if (i, j) != (2, 1)]
    more = spark.createDataFrame([(min(e), max(e)) for e in planted], "src long, dst long")
    return D.pseudo_clique_counts(Graph(edges.unionAll(more)), 7)
