"""Enumeration of matchings by joins, one level for each pattern vertex.

A matching is a row m0..m{n-1}.  A level extends rows by one arc join; each
further pattern edge to an earlier vertex is a semi join, each forbidden one
(vertex-induced) an anti join; vertices not tied by an edge must differ.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutloom.operators import kernel
from cutloom.operators.graph import Graph
from cutloom.patterns.algebra import Pattern, automorphisms, restrictions
from cutloom.plans.search import Plan, best_direct, greedy_order

Filter = Callable[[DataFrame, list[int]], DataFrame]


def _arcs(g: Graph, p: Pattern, a: int, b: int) -> DataFrame:
    """arcs with the labels that pattern vertices a and b ask for."""
    if p.labels is None:
        return g.pairs
    arcs = g.arcs
    for column, v in (("lu", a), ("lv", b)):
        if p.label(v) is not None:
            arcs = arcs.where(F.col(column) == F.lit(p.label(v)))
    return arcs.select("u", "v")


def extend(rows: DataFrame, g: Graph, p: Pattern, before: list[int], w: int, induced: str = "edge", pinned=(), arcs: DataFrame | None = None) -> DataFrame:
    """Rows over ``before`` extended by pattern vertex ``w``."""
    back = [u for u in before if p.adjacent(u, w)]
    if not back:
        raise ValueError("the order isn't connected")
    anchor = back[-1]
    step = (_arcs(g, p, anchor, w) if arcs is None else arcs).select(F.col("u").alias(f"__u{w}"), F.col("v").alias(f"m{w}"))
    out = rows.join(step, F.col(f"m{anchor}") == F.col(f"__u{w}")).drop(f"__u{w}")
    condition = [F.col(f"m{u}") != F.col(f"m{w}") for u in before if u not in back]
    condition += [F.col(f"m{a}") < F.col(f"m{b}") for a, b in pinned if (a == w and b in before) or (b == w and a in before)]
    for c in condition:
        out = out.where(c)
    for u in before:
        if u == anchor or (u not in back and induced != "vertex"):
            continue
        check = g.pairs.select(F.col("u").alias("__a"), F.col("v").alias("__b"))
        out = out.join(check, (F.col(f"m{u}") == F.col("__a")) & (F.col(f"m{w}") == F.col("__b")), "left_semi" if u in back else "left_anti")
    return out


def start(g: Graph, p: Pattern, a: int, b: int, pinned=()) -> DataFrame:
    rows = _arcs(g, p, a, b).select(F.col("u").alias(f"m{a}"), F.col("v").alias(f"m{b}"))
    for x, y in pinned:
        if {x, y} == {a, b}:
            rows = rows.where(F.col(f"m{x}") < F.col(f"m{y}"))
    return rows


def single(g: Graph, p: Pattern) -> DataFrame:
    rows = g.degrees().select(F.col("v").alias("m0"))
    if p.labels is not None and p.label(0) is not None:
        rows = rows.join(g.vertices.where(F.col("label") == F.lit(p.label(0))).select(F.col("v").alias("m0")), "m0", "left_semi")
    return rows


def enumerate_matchings(g: Graph, p: Pattern, order: tuple[int, ...] | None = None, induced: str = "edge", pinned=(), replay: int = 0, limit: Filter | None = None, each_level: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """All matchings m0..m{n-1}; with ``pinned`` those that keep its order of images.

    ``replay`` enumerates the first so many levels once for each embedding of
    their sub-pattern and lets each row stand for all its relabellings.
    ``limit`` filters rows as soon as the vertices it names are bound.
    """
    order = tuple(order or greedy_order(p))
    if p.n == 1:
        return single(g, p)
    hook = each_level or (lambda df: df)
    cut_rows = limit or (lambda df, bound: df)
    if replay >= 2:
        q = p.induced(list(order[:replay]))
        rows = enumerate_matchings(g, q, tuple(range(q.n)), induced, restrictions(q))
        images = F.array(*[F.struct(*[F.col(f"m{s[i]}").alias(f"m{order[i]}") for i in range(replay)]) for s in automorphisms(q)])
        rows = rows.select(F.explode(images).alias("x")).select("x.*")
        bound = list(order[:replay])
        for k in range(2, replay + 1):
            rows = cut_rows(rows, bound[:k])
    else:
        rows = hook(cut_rows(start(g, p, order[0], order[1], pinned), list(order[:2])))
        if induced == "vertex" and not p.adjacent(order[0], order[1]):
            raise ValueError("the order isn't connected")
        bound = list(order[:2])
    for w in order[len(bound):]:
        rows = extend(rows, g, p, bound, w, induced, pinned)
        bound.append(w)
        rows = hook(cut_rows(rows, bound))
    return rows.select(*[f"m{v}" for v in range(p.n)])


def count_matchings(g: Graph, p: Pattern, order: tuple[int, ...] | None = None, induced: str = "edge", pinned=(), replay: int = 0) -> int:
    """How many matchings enumerate_matchings() makes, by the kernel where the graph fits a task; ``pinned`` is to break whole symmetries."""
    order = tuple(order or greedy_order(p))
    if p.n == 1 or p.labels is not None or not g.fits():
        return enumerate_matchings(g, p, order, induced, pinned, replay).count()
    return kernel.counts(g, [kernel.walk(p, order, pinned, induced, replay=replay)])[0]


def embeddings(g: Graph, p: Pattern, induced: str = "edge", plan: Plan | None = None) -> DataFrame:
    """One matching of each embedding: symmetry is broken by restrictions."""
    plan = plan or best_direct(p)
    return enumerate_matchings(g, p, plan.order, induced, plan.pinned or restrictions(p))


def write_embeddings(g: Graph, p: Pattern, path: str, induced: str = "edge") -> None:
    """For applications that need every embedding: enumerate and write, without decomposition."""
    embeddings(g, p, induced).write.mode("overwrite").parquet(path)


def direct_count(g: Graph, p: Pattern, induced: str = "edge", plan: Plan | None = None) -> DataFrame:
    """One row cnt: the embeddings."""
    return embeddings(g, p, induced, plan).agg(F.count(F.lit(1)).alias("cnt"))


def set_rows(g: Graph, p: Pattern, order: tuple[int, ...] | None = None, induced: str = "edge", pinned=()) -> DataFrame:
    """One row cnt: matchings with neighbour sets as arrays; the last level is the size of a set, never exploded.

    Whole neighbour arrays move with the rows, so this is for light vertices.
    """
    order = tuple(order or greedy_order(p))
    if p.n < 3:
        return enumerate_matchings(g, p, order, induced, pinned).agg(F.count(F.lit(1)).alias("cnt"))
    adj = g.adjacency().select("v", "nbrs")

    def candidates(w: int, before: list[int]):
        back = [u for u in before if p.adjacent(u, w)]
        s = F.col(f"n{back[0]}")
        for u in back[1:]:
            s = F.array_intersect(s, F.col(f"n{u}"))
        if induced == "vertex":
            for u in before:
                if u not in back:
                    s = F.array_except(s, F.col(f"n{u}"))
        low = [F.col(f"m{a}") for a, b in pinned if b == w and a in before]
        high = [F.col(f"m{b}") for a, b in pinned if a == w and b in before]
        others = [F.col(f"m{u}") for u in before if u not in back]

        def keep(x):
            ok = F.lit(True)
            for y in low:
                ok = ok & (x > y)
            for y in high:
                ok = ok & (x < y)
            for y in others:
                ok = ok & (x != y)
            return ok

        return F.filter(s, keep) if low or high or others else s

    rows = adj.select(F.col("v").alias(f"m{order[0]}"), F.col("nbrs").alias(f"n{order[0]}"))
    for i in range(1, p.n - 1):
        w = order[i]
        rows = rows.withColumn(f"m{w}", F.explode(candidates(w, list(order[:i]))))
        needed = any(w != x and (p.adjacent(w, x) or induced == "vertex") for x in order[i + 1:])
        if needed:
            rows = rows.join(adj.select(F.col("v").alias(f"m{w}"), F.col("nbrs").alias(f"n{w}")), f"m{w}")
    return rows.agg(F.coalesce(F.sum(F.size(candidates(order[-1], list(order[:-1]))).cast("long")), F.lit(0)).cast("long").alias("cnt"))


def merged_enumeration(g: Graph, plans: list[Plan]) -> dict[Pattern, DataFrame]:
    """Matchings of several direct plans; levels that agree (prefix pattern, restrictions so far) are made once and kept."""
    shared: dict[tuple, DataFrame] = {}
    uses: dict[tuple, int] = {}

    def keys(plan: Plan) -> list[tuple]:
        p = plan.pattern
        out = []
        for i in range(2, p.n + 1):
            at = {v: k for k, v in enumerate(plan.order[:i])}
            q = p.induced(list(plan.order[:i]))
            own = tuple(sorted((at[a], at[b]) for a, b in plan.pinned if a in at and b in at))
            out.append((q, own))
        return out

    for plan in plans:
        for k in keys(plan):
            uses[k] = uses.get(k, 0) + 1
    out = {}
    for plan in plans:
        levels = keys(plan)
        rows = None
        for i, k in enumerate(levels):
            if k not in shared:
                q, own = k
                shared[k] = start(g, q, 0, 1, own) if i == 0 else extend(shared[levels[i - 1]], g, q, list(range(q.n - 1)), q.n - 1, "edge", own)
                if uses[k] > 1 and i > 0:
                    shared[k] = shared[k].persist()
            rows = shared[k]
        out[plan.pattern] = rows.select(*[F.col(f"m{plan.order.index(v)}").alias(f"m{v}") for v in range(plan.pattern.n)])
    return out
