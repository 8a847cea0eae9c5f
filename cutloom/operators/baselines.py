"""The engines that decomposition is measured against, as runnable counts."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutloom.operators import kernel
from cutloom.operators.decompose import clique_count, count_with_cut
from cutloom.operators.enumerate import enumerate_matchings, merged_enumeration, set_rows
from cutloom.operators.graph import Graph, reliable
from cutloom.patterns.algebra import Pattern, automorphisms, canonical_code, restrictions
from cutloom.patterns.catalogue import clique, connected_patterns
from cutloom.plans.cost import DEFAULT, UniformModel
from cutloom.plans.search import all_orders, best_direct, best_restrictions, bound_choice, greedy_order


def _named(rows: DataFrame, p: Pattern) -> DataFrame:
    return rows.select(F.lit(p.name).alias("pattern"), F.lit(p.n).alias("n"), F.lit(p.m).alias("m"), F.col("cnt").cast("long").alias("cnt"))


def _all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionAll, frames)


def set_enumeration(g: Graph, patterns: list[Pattern], induced: str = "vertex") -> DataFrame:
    """Compiled set enumeration: no cut, the order by the uniform model, neighbour sets as arrays.

    Where the neighbour lists fit a task, the kernel grows the sets, all patterns in one job.
    """
    if g.fits():
        plans = [best_direct(p, DEFAULT) for p in patterns]
        found = kernel.counts(g, [kernel.walk(p, plan.order, restrictions(p), induced) for p, plan in zip(patterns, plans)])
        return g.spark.createDataFrame([(p.name, p.n, p.m, n) for p, n in zip(patterns, found)], "pattern string, n int, m int, cnt long")
    out = []
    for p in patterns:
        plan = best_direct(p, DEFAULT)
        out.append(_named(set_rows(g, p, plan.order, induced, restrictions(p)), p))
    return _all(out)


def symmetry(g: Graph, patterns: list[Pattern], induced: str = "vertex") -> DataFrame:
    """Symmetry-aware matching: one restriction set, joins."""
    return _all([_named(enumerate_matchings(g, p, greedy_order(p), induced, restrictions(p)).agg(F.count(F.lit(1)).alias("cnt")), p) for p in patterns])


def restricted(g: Graph, patterns: list[Pattern], induced: str = "vertex") -> DataFrame:
    """The restriction set and order that the cost model likes best."""
    out = []
    for p in patterns:
        plan = best_restrictions(p)
        out.append(_named(enumerate_matchings(g, p, plan.order, induced, plan.pinned).agg(F.count(F.lit(1)).alias("cnt")), p))
    return _all(out)


def restricted_count(g: Graph, patterns: list[Pattern]) -> DataFrame:
    """As restricted(), edge-induced, but last levels that don't see each other become arithmetic: k leaves of one vertex are a binomial."""
    out = []
    for p in patterns:
        leaves: dict[int, list[int]] = {}
        for v in range(p.n):
            if len(p.neighbours[v]) == 1 and p.n > 2:
                leaves.setdefault(next(iter(p.neighbours[v])), []).append(v)
        hub, own = max(leaves.items(), key=lambda x: len(x[1]), default=(None, []))
        core = [v for v in range(p.n) if v not in own]
        q = p.induced(core) if hub is not None else None
        if q is None or q.n < 2 or not q.connected():
            if q is not None and q.n == 1:
                d = F.col("deg")
                term = reduce(lambda a, i: a * (d - i), range(len(own)), F.lit(1).cast("decimal(38,0)"))
                falling = g.degrees().select(term.cast("decimal(38,0)").alias("x")).agg(F.coalesce(F.sum("x"), F.lit(0)).cast("long").alias("s"))
                rows = falling.select(F.expr(f"s div {len(automorphisms(p))}").alias("cnt"))
                out.append(_named(rows, p))
            else:
                plan = best_restrictions(p)
                out.append(_named(enumerate_matchings(g, p, plan.order, "edge", plan.pinned).agg(F.count(F.lit(1)).alias("cnt")), p))
            continue
        at = core.index(hub)
        rows = enumerate_matchings(g, q, greedy_order(q))
        rows = rows.join(g.degrees().select(F.col("v").alias(f"m{at}"), "deg"), f"m{at}")
        # neighbours of the hub that the core already uses
        used = len(q.neighbours[at])
        free = F.col("deg") - used
        for v in range(q.n):
            if v != at and not q.adjacent(at, v):
                tie = g.pairs.select(F.col("u").alias(f"m{at}"), F.col("v").alias(f"m{v}"), F.lit(1).alias(f"t{v}"))
                rows = rows.join(tie, [f"m{at}", f"m{v}"], "left")
                free = free - F.coalesce(F.col(f"t{v}"), F.lit(0))
        term = reduce(lambda a, i: a * F.greatest(free - i, F.lit(0)), range(len(own)), F.lit(1).cast("long"))
        total = rows.agg(F.coalesce(F.sum(term.cast("decimal(38,0)")), F.lit(0)).cast("long").alias("s"))
        out.append(_named(total.select(F.expr(f"s div {len(automorphisms(p))}").alias("cnt")), p))
    return _all(out)


def oblivious(g: Graph, k: int) -> DataFrame:
    """Pattern-oblivious: all connected vertex sets of size k are grown, then each is classified by its edges (vertex-induced).

    Where the neighbour lists fit a task, the kernel grows each set once and nothing is shuffled but counts.
    """
    shapes = kernel.set_shapes(g, k) if g.fits() else _set_shapes(g, k)
    names = {canonical_code(p): p for p in connected_patterns(k)}
    from itertools import permutations

    rows = set()
    for p in names.values():
        for a in permutations(range(k)):
            mask = sum((1 << (a[x] * k + a[y])) | (1 << (a[y] * k + a[x])) for x, y in p.edges)
            rows.add((mask, p.name, p.n, p.m))
    table = g.spark.createDataFrame(sorted(rows), "mask long, pattern string, n int, m int")
    counts = shapes.join(F.broadcast(table), "mask").groupBy("pattern").agg(F.sum("c").alias("c"))
    every = g.spark.createDataFrame([(p.name, p.n, p.m) for p in names.values()], "pattern string, n int, m int")
    return every.join(counts, "pattern", "left").select("pattern", "n", "m", F.coalesce("c", F.lit(0)).cast("long").alias("cnt"))


def _set_shapes(g: Graph, k: int) -> DataFrame:
    """(mask, c) by joins; the sets are shuffled."""
    sets = g.edges.select(F.array("src", "dst").alias("s"))
    for _ in range(k - 2):
        grown = sets.select("s", F.explode("s").alias("u")).join(g.pairs, "u").where(~F.array_contains("s", F.col("v")))
        sets = grown.select(F.array_sort(F.concat("s", F.array("v"))).alias("s")).distinct()
    inner = sets.select("s", F.posexplode("s").alias("i", "u")).join(g.pairs, "u").where(F.array_contains("s", F.col("v")))
    bit = F.expr(f"shiftleft(1L, CAST(i * {k} + array_position(s, v) - 1 AS INT))")
    return inner.select("s", bit.alias("b")).groupBy("s").agg(F.sum("b").alias("mask")).groupBy("mask").agg(F.count(F.lit(1)).alias("c"))


def relational(g: Graph, p: Pattern, view: str = "cutloom_pairs") -> DataFrame:
    """Plain SQL self-joins of the edge table; every embedding is made, then duplicates are removed."""
    g.pairs.createOrReplaceTempView(view)
    edges = sorted(p.edges)
    bound: dict[int, str] = {}
    where = []
    for i, (a, b) in enumerate(edges):
        for v, column in ((a, f"e{i}.u"), (b, f"e{i}.v")):
            if v in bound:
                where.append(f"{bound[v]} = {column}")
            else:
                bound[v] = column
    where += [f"{bound[a]} <> {bound[b]}" for a in range(p.n) for b in range(a) if not p.adjacent(a, b)]
    ends = ", ".join(f"concat(least({bound[a]}, {bound[b]}), '-', greatest({bound[a]}, {bound[b]}))" for a, b in edges)
    sql = f"SELECT count(*) AS cnt FROM (SELECT DISTINCT concat_ws(',', sort_array(array({ends}))) AS e FROM {', '.join(f'{view} e{i}' for i in range(len(edges)))} WHERE {' AND '.join(where) or 'true'})"
    return _named(g.spark.sql(sql), p)


def bfs(g: Graph, p: Pattern, induced: str = "edge") -> DataFrame:
    """Level-synchronous: each frontier is written to the checkpoint folder before the next is made."""
    plan = best_direct(p)
    rows = enumerate_matchings(g, p, plan.order, induced, plan.pinned, each_level=reliable)
    return _named(rows.agg(F.count(F.lit(1)).alias("cnt")), p)


#: The kernel's adjacency goes to every task, so its size is checked: arcs.
KERNEL_ARCS = 20_000_000


def dfs(g: Graph, p: Pattern, induced: str = "edge", most_arcs: int = KERNEL_ARCS) -> DataFrame:
    """Depth-first set enumeration in an Arrow kernel over the start vertices, with the adjacency broadcast.

    Graphs beyond ``most_arcs`` arcs run the same order and restrictions as joins.
    """
    plan = best_direct(p)
    if 2 * g.edges.count() > most_arcs:
        rows = enumerate_matchings(g, p, plan.order, induced, plan.pinned)
        return _named(rows.agg(F.count(F.lit(1)).alias("cnt")), p)
    adj = g.adjacency().select("v", "nbrs")
    near = g.spark.sparkContext.broadcast({r["v"]: np.asarray(r["nbrs"], np.int64) for r in adj.collect()})
    order, pinned = list(plan.order), list(plan.pinned)

    def run(batches):
        table, empty = near.value, np.zeros(0, np.int64)

        def below(images: dict[int, int], i: int) -> int:
            v = order[i]
            back = [images[u] for u in order[:i] if p.adjacent(u, v)]
            found = table.get(back[0], empty)
            for b in back[1:]:
                found = np.intersect1d(found, table.get(b, empty), assume_unique=True)
            for u in order[:i]:
                if not p.adjacent(u, v):
                    found = np.setdiff1d(found, table.get(images[u], empty), assume_unique=True) if induced == "vertex" else found
                    found = found[found != images[u]]
            for a, b in pinned:
                if b == v and a in images:
                    found = found[found > images[a]]
                if a == v and b in images:
                    found = found[found < images[b]]
            if i == len(order) - 1:
                return len(found)
            return sum(below(images | {v: x}, i + 1) for x in found.tolist())

        for batch in batches:
            yield pa.RecordBatch.from_pydict({"c": [sum(below({order[0]: v}, 1) for v in batch.column(0).to_pylist())]})

    rows = adj.select("v").repartition(4 * g.spark.sparkContext.defaultParallelism).mapInArrow(run, "c long")
    return _named(rows.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("cnt")), p)


def native4(g: Graph) -> DataFrame:
    """Expert formulas for the six patterns of four vertices, edge-induced, from degrees, triangles on edges and common neighbours."""
    d = g.degrees()
    a, b = g.pairs.select(F.col("u").alias("w"), F.col("v").alias("x")), g.pairs.select(F.col("u").alias("w"), F.col("v").alias("y"))
    common = a.join(b, "w").where("x < y").groupBy("x", "y").agg(F.count(F.lit(1)).alias("c"))
    on_edge = g.edges.join(common, (F.col("src") == F.col("x")) & (F.col("dst") == F.col("y"))).select("src", "dst", F.col("c").alias("t"))
    on_vertex = on_edge.select(F.explode(F.array("src", "dst")).alias("v"), "t").groupBy("v").agg(F.sum("t").alias("t2"))
    star = d.agg(F.sum(F.expr("deg * (deg - 1) * (deg - 2) div 6")).alias("star"))
    both = g.edges.join(d.select(F.col("v").alias("src"), F.col("deg").alias("ds")), "src").join(d.select(F.col("v").alias("dst"), F.col("deg").alias("dd")), "dst")
    paths = both.agg(F.sum((F.col("ds") - 1) * (F.col("dd") - 1)).alias("paths"))
    edge = on_edge.agg(F.coalesce(F.sum("t"), F.lit(0)).alias("t3"), F.coalesce(F.sum(F.expr("t * (t - 1) div 2")), F.lit(0)).alias("diamond"))
    tail = on_vertex.join(d, "v").agg(F.coalesce(F.sum(F.expr("t2 div 2 * (deg - 2)")), F.lit(0)).alias("tail"))
    square = common.agg(F.coalesce(F.sum(F.expr("c * (c - 1) div 2")), F.lit(0)).alias("c4"))
    k4 = clique_count(g, clique(4)).select(F.col("cnt").alias("k4"))
    row = reduce(lambda x, y: x.join(F.broadcast(y)), [star, paths, edge, tail, square, k4])
    values = {"01 02 03": "star", "01 02 13": "paths - t3", "01 02 03 12": "tail", "01 02 13 23": "c4 div 2", "01 02 03 12 13": "diamond", "01 02 03 12 13 23": "k4"}
    out = []
    for p in connected_patterns(4):
        code = canonical_code(p)
        text = next(v for k, v in values.items() if canonical_code(Pattern.parse(k)) == code)
        out.append((p, text))
    table = F.explode(F.array(*[F.struct(F.lit(p.name).alias("pattern"), F.lit(p.n).alias("n"), F.lit(p.m).alias("m"), F.expr(f"CAST(coalesce({t}, 0) AS BIGINT)").alias("cnt")) for p, t in out]))
    return row.select(table.alias("x")).select("x.*")


def bound_chosen(g: Graph, p: Pattern) -> int:
    """Decomposition with the cut of the smallest worst-case bound."""
    cut = bound_choice(p)
    return clique_count(g, p).first()["cnt"] if cut is None else count_with_cut(g, p, cut)


def perfect(g: Graph, p: Pattern, induced: str = "edge", most: int = 24) -> tuple[tuple[int, ...], float, int]:
    """Set enumeration with an ideal model: every order (up to ``most``) is run; the fastest, its seconds and the count."""
    import time

    best = None
    for order in all_orders(p)[:most]:
        began = time.perf_counter()
        n = enumerate_matchings(g, p, order, induced, restrictions(p)).count()
        took = time.perf_counter() - began
        best = (order, took, n) if best is None or took < best[1] else best
    return best


def shared_pair(g: Graph) -> DataFrame:
    """The tailed triangle and the 4-clique through one shared triangle level."""
    model = UniformModel(1e5, 20)
    tail, full = Pattern.parse("01 02 12 03"), clique(4)
    plans = [best_direct(p, model, []) for p in (tail, full)]
    rows = merged_enumeration(g, plans)
    return _all([_named(r.agg(F.expr(f"count(1) div {len(automorphisms(p))}").alias("cnt")), p) for p, r in rows.items()])
