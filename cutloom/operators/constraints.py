"""Label constraints: conjunctions of conditions on the labels of a few pattern vertices."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cutloom.operators.decompose import WIDE
from cutloom.operators.enumerate import enumerate_matchings
from cutloom.operators.fragments import collision_rows, part_rows
from cutloom.operators.graph import Graph
from cutloom.patterns.algebra import Pattern, automorphisms
from cutloom.plans.cuts import all_cuts, joinable, parts
from cutloom.plans.search import greedy_order


@dataclass(frozen=True)
class Sub:
    """A condition on the labels of some vertices; ``kind`` is differ or equal, or custom with ``test``."""

    vertices: tuple[int, ...]
    kind: str
    test: Callable[[list[Column]], Column] | None = None

    def holds(self, labels: list[Column]) -> Column:
        if self.kind == "custom":
            return self.test(labels)
        if self.kind == "equal":
            pairs = [labels[0] == x for x in labels[1:]]
        else:
            pairs = [a != b for a, b in combinations(labels, 2)]
        out = F.lit(True)
        for x in pairs:
            out = out & x
        return out


@dataclass(frozen=True)
class Constraint:
    subs: tuple[Sub, ...]


def cuts_supporting(p: Pattern, c: Constraint) -> list[tuple[int, ...]]:
    """Usable cuts one of whose parts holds each sub-constraint whole."""
    return [cut for cut in all_cuts(p) if joinable(p, cut) and all(any(set(s.vertices) <= set(x.vertices) for x in parts(p, cut)) for s in c.subs)]


def preserving(p: Pattern, c: Constraint) -> list[tuple[int, ...]]:
    """Automorphisms that map the constraint onto itself."""
    mine = {(s.kind, frozenset(s.vertices), id(s.test)) for s in c.subs}
    return [a for a in automorphisms(p) if {(s.kind, frozenset(a[v] for v in s.vertices), id(s.test)) for s in c.subs} == mine]


def _labelled(rows: DataFrame, g: Graph, vertices) -> DataFrame:
    for v in vertices:
        if f"l{v}" not in rows.columns:
            rows = rows.join(g.vertices.select(F.col("v").alias(f"m{v}"), F.col("label").alias(f"l{v}")), f"m{v}")
    return rows


def _kept(rows: DataFrame, g: Graph, c: Constraint, bound) -> DataFrame:
    for s in c.subs:
        if set(s.vertices) <= set(bound):
            rows = _labelled(rows, g, s.vertices).where(s.holds([F.col(f"l{v}") for v in s.vertices]))
    return rows.drop(*[x for x in rows.columns if x.startswith("l")])


def constrained_count(g: Graph, p: Pattern, c: Constraint, cut: tuple[int, ...] | None = None, via: str = "auto") -> DataFrame:
    """One row (matchings, subgraphs): satisfying matchings, and those modulo the automorphisms that keep the constraint.

    Sub-constraints filter the parts that hold them and the collisions alike;
    without a supporting cut, all matchings are enumerated and filtered.
    """
    cuts = [cut] if cut is not None else cuts_supporting(p, c)
    group = len(preserving(p, c))
    if via == "direct" or not cuts:
        rows = _kept(enumerate_matchings(g, p, greedy_order(p)), g, c, range(p.n))
        total = rows.agg(F.count(F.lit(1)).cast(WIDE).alias("t"))
    else:
        chosen = min(cuts, key=lambda x: (max(len(y.vertices) for y in parts(p, x)), len(x)))
        keys = [f"m{v}" for v in chosen]
        tables = [_kept(part_rows(g, p, x), g, c, x.vertices).groupBy(*keys).agg(F.count(F.lit(1)).alias(f"n{i}")) for i, x in enumerate(parts(p, chosen))]
        rows, factor = tables[0], F.col("n0").cast(WIDE)
        for i, t in enumerate(tables[1:], 1):
            rows, factor = rows.join(t, keys), (factor * F.col(f"n{i}").cast("decimal(18,0)")).cast(WIDE)
        total = rows.agg(F.coalesce(F.sum(factor), F.lit(0)).cast(WIDE).alias("t"))
        clashes = collision_rows(g, p, chosen)
        if clashes is not None:
            less = _kept(clashes, g, c, range(p.n)).agg(F.count(F.lit(1)).cast(WIDE).alias("x"))
            total = total.join(F.broadcast(less)).select((F.col("t") - F.col("x")).cast(WIDE).alias("t"))
    return total.select(F.col("t").cast("long").alias("matchings"), F.expr(f"CAST(t AS BIGINT) div {group}").alias("subgraphs"))


def demo() -> tuple[Pattern, Constraint, tuple[int, ...]]:
    """The stand-in of the five-vertex query: labels of 0, 1, 2 differ pairwise, those of 1, 3, 4 are equal; cut 0, 1, 3."""
    return Pattern.parse("01 03 13 02 12 14 34"), Constraint((Sub((0, 1, 2), "differ"), Sub((1, 3, 4), "equal"))), (0, 1, 3)
