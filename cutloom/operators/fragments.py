"""Fragments: matchings of the parts of a cut, each with the number of whole matchings it grows into.

weight = product of the other parts' counts at the cut match, less the
collision matchings that project onto the fragment.  A fragment row has the
pattern's columns m0..m{n-1}, null where a vertex lies outside the part.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutloom.operators.enumerate import enumerate_matchings
from cutloom.operators.graph import Graph
from cutloom.patterns.algebra import Pattern
from cutloom.plans.cuts import Part, collisions, joinable, part_pattern, parts
from cutloom.plans.search import greedy_order, search

LimitOf = Callable[[tuple[int, ...]], Callable | None]


def usable_cut(p: Pattern, cut: tuple[int, ...] | None = None) -> tuple[int, ...] | None:
    """The given cut or the planner's; None for patterns without one, whose fragments are whole matchings."""
    if cut is not None:
        if not joinable(p, cut):
            raise ValueError("a part of this cut isn't connected")
        return tuple(cut)
    plan = search(p, allow_direct=False)
    return plan.cut if plan.kind == "cut" else None


def part_rows(g: Graph, p: Pattern, part: Part, limit=None) -> DataFrame:
    """Matchings of a part, in the pattern's column names."""
    q = part_pattern(p, part)
    rows = enumerate_matchings(g, q, greedy_order(q, tuple(range(len(part.cut)))), limit=None if limit is None else limit(part.vertices))
    return rows.select(*[F.col(f"m{i}").alias(f"m{v}") for i, v in enumerate(part.vertices)])


def collision_rows(g: Graph, p: Pattern, cut: tuple[int, ...], limit=None) -> DataFrame | None:
    """All matchings of all quotients, laid out on the pattern's vertices."""
    out = []
    for c in collisions(p, cut):
        q = c.quotient
        names = tuple(c.block_of.index(b) for b in range(q.n))
        rows = enumerate_matchings(g, q, greedy_order(q), limit=None if limit is None else limit(names, c.block_of))
        out.append(rows.select(*[F.col(f"m{c.block_of[v]}").alias(f"m{v}") for v in range(p.n)]))
    return reduce(DataFrame.unionAll, out) if out else None


def fragments(g: Graph, p: Pattern, cut: tuple[int, ...] | None = None, limit=None) -> DataFrame:
    """(part, m0..m{n-1}, weight) of every fragment with weight above zero.

    All fragments of a part come from its full enumeration, so they are passed
    all or none; the parts cover the pattern since each vertex off the cut lies
    in one component.
    """
    columns = [f"m{v}" for v in range(p.n)]
    chosen = usable_cut(p, cut)
    if chosen is None:
        return enumerate_matchings(g, p, limit=None if limit is None else limit(tuple(range(p.n)))).select(F.lit(0).alias("part"), *columns, F.lit(1).cast("long").alias("weight"))
    pieces = parts(p, chosen)
    assert {v for x in pieces for v in x.vertices} == set(range(p.n))
    keys = [f"m{v}" for v in chosen]
    rows = [part_rows(g, p, x, limit) for x in pieces]
    counts = [r.groupBy(*keys).agg(F.count(F.lit(1)).alias(f"n{i}")) for i, r in enumerate(rows)]
    clashes = collision_rows(g, p, chosen, limit)
    out = []
    for i, part in enumerate(pieces):
        own = [f"m{v}" for v in part.vertices]
        others = reduce(lambda a, b: a.join(b, keys), [c for j, c in enumerate(counts) if j != i])
        product = reduce(lambda a, b: a * b, [F.col(f"n{j}") for j in range(len(pieces)) if j != i])
        grown = rows[i].join(others, keys).withColumn("most", product).select(*own, "most")
        if clashes is not None:
            taken = clashes.groupBy(*own).agg(F.count(F.lit(1)).alias("less"))
            grown = grown.join(taken, own, "left")
            weight = F.col("most") - F.coalesce("less", F.lit(0))
        else:
            weight = F.col("most")
        grown = grown.withColumn("weight", weight.cast("long")).where("weight > 0")
        out.append(grown.select(F.lit(i).alias("part"), *[F.col(c) if c in own else F.lit(None).cast("long").alias(c) for c in columns], "weight"))
    return reduce(DataFrame.unionAll, out)


def process_fragments(g: Graph, p: Pattern, fn: Callable[[DataFrame], DataFrame], cut: tuple[int, ...] | None = None) -> DataFrame:
    """Hand the fragments to a callback, in the plan; an Arrow callback uses mapInArrow itself."""
    return fn(fragments(g, p, cut))


def materialize(g: Graph, p: Pattern, some: DataFrame, num: int, cut: tuple[int, ...] | None = None) -> DataFrame:
    """Up to ``num`` whole matchings of each fragment: part, its fragment as f0.., and m0..; smallest ids first."""
    chosen = usable_cut(p, cut)
    columns = [f"m{v}" for v in range(p.n)]
    if chosen is None:
        return some.select("part", *[F.col(c).alias("f" + c[1:]) for c in columns], *columns)
    keys = [f"m{v}" for v in chosen]
    pieces = parts(p, chosen)
    out = []
    for i, part in enumerate(pieces):
        own = [f"m{v}" for v in part.vertices]
        rows = some.where(F.col("part") == i).select(*own)
        for j, other in enumerate(pieces):
            if j != i:
                rows = rows.join(part_rows(g, p, other), keys)
        free = [(a, b) for x in range(len(pieces)) for y in range(x) for a in pieces[x].component for b in pieces[y].component]
        for a, b in free:
            rows = rows.where(F.col(f"m{a}") != F.col(f"m{b}"))
        rank = F.row_number().over(Window.partitionBy(*own).orderBy(*columns))
        rows = rows.withColumn("__k", rank).where(F.col("__k") <= num)
        out.append(rows.select(F.lit(i).alias("part"), *[(F.col(c) if c in own else F.lit(None).cast("long")).alias("f" + c[1:]) for c in columns], *columns))
    return reduce(DataFrame.unionAll, out)


def domains(g: Graph, p: Pattern, cut: tuple[int, ...] | None = None) -> DataFrame:
    """(role, v): every graph vertex that a pattern vertex is matched to, from fragments alone."""
    columns = [f"m{v}" for v in range(p.n)]
    roles = F.explode(F.array(*[F.struct(F.lit(i).alias("role"), F.col(c).alias("v")) for i, c in enumerate(columns)]))
    return fragments(g, p, cut).select(roles.alias("x")).select("x.role", "x.v").where("v IS NOT NULL").distinct()


def support(g: Graph, p: Pattern, cut: tuple[int, ...] | None = None) -> DataFrame:
    """One row support: the size of the smallest domain, 0 if a role has none."""
    sizes = domains(g, p, cut).groupBy("role").agg(F.count(F.lit(1)).alias("n"))
    return sizes.agg(F.when(F.count(F.lit(1)) == p.n, F.min("n")).otherwise(0).alias("support"))


def role_vertices(g: Graph, leaves: int) -> DataFrame:
    """(v): the centres of stars with ``leaves`` leaves.  Existence needs only the degree."""
    return g.degrees().where(F.col("deg") >= leaves).select("v")


class StampedTable:
    """A hash table cleared in constant time: entries carry the stamp of the round that wrote them.

    For kernels that keep one discount table over many cut matches; keyed
    DataFrames have the cut match in the key and need none.
    """

    def __init__(self, bits: int = 64):
        self.limit, self.stamp, self.cells = 1 << bits, 1, {}

    def clear(self) -> None:
        self.stamp += 1
        if self.stamp >= self.limit:
            self.cells, self.stamp = {}, 1

    def add(self, key, amount: int = 1) -> None:
        stamp, value = self.cells.get(key, (0, 0))
        self.cells[key] = (self.stamp, amount + (value if stamp == self.stamp else 0))

    def get(self, key) -> int:
        stamp, value = self.cells.get(key, (0, 0))
        return value if stamp == self.stamp else 0
