"""Vertex cuts of a pattern, the parts they leave, and the collisions between parts."""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from functools import lru_cache
from itertools import combinations

from cutloom.patterns.algebra import Pattern, automorphisms, canonical_code


@dataclass(frozen=True)
class Part:
    """A cut with one of the components it leaves; ``vertices`` are those of the pattern, cut first."""

    cut: tuple[int, ...]
    component: tuple[int, ...]

    @property
    def vertices(self) -> tuple[int, ...]:
        return (*self.cut, *self.component)


@dataclass(frozen=True)
class Collision:
    """A gluing of vertices of different components: ``block_of`` names each pattern vertex's vertex in the quotient."""

    quotient: Pattern
    block_of: tuple[int, ...]


def is_cut(p: Pattern, cut: frozenset[int]) -> bool:
    return len(p.components(cut)) > 1


def all_cuts(p: Pattern, up_to_symmetry: bool = False) -> list[tuple[int, ...]]:
    """Vertex sets whose removal leaves two components or more."""
    found = [c for k in range(1, p.n - 1) for c in combinations(range(p.n), k) if is_cut(p, frozenset(c))]
    if not up_to_symmetry:
        return found
    group, seen, out = automorphisms(p), set(), []
    for c in found:
        if c not in seen:
            seen |= {tuple(sorted(g[v] for v in c)) for g in group}
            out.append(c)
    return out


def parts(p: Pattern, cut: tuple[int, ...]) -> list[Part]:
    return [Part(tuple(cut), tuple(sorted(c))) for c in p.components(frozenset(cut))]


def part_pattern(p: Pattern, part: Part) -> Pattern:
    return p.induced(list(part.vertices))


def joinable(p: Pattern, cut: tuple[int, ...]) -> bool:
    """Whether every part is connected, so that none needs a product of unrelated vertices."""
    return all(part_pattern(p, x).connected() for x in parts(p, cut))


@lru_cache(maxsize=20_000)
def collisions(p: Pattern, cut: tuple[int, ...]) -> tuple[Collision, ...]:
    """Every way to glue vertices of different components, at most one of each to a block; the trivial way left out.

    Vertices whose labels differ are never glued.
    """
    component = {v: i for i, part in enumerate(parts(p, cut)) for v in part.component}
    free = sorted(component)
    out: list[Collision] = []

    def place(i: int, blocks: list[list[int]]) -> None:
        if i == len(free):
            if len(blocks) < len(free):
                number = {v: k for k, v in enumerate(cut)} | {v: len(cut) + k for k, b in enumerate(blocks) for v in b}
                block_of = [number[v] for v in range(p.n)]
                out.append(Collision(p.glued(block_of), tuple(block_of)))
            return
        v = free[i]
        for b in blocks:
            if all(component[u] != component[v] for u in b) and all(p.label(u) is None or p.label(v) is None or p.label(u) == p.label(v) for u in b):
                b.append(v)
                place(i + 1, blocks)
                b.pop()
        place(i + 1, [*blocks, [v]])

    place(0, [])
    return tuple(out)


def grouped_collisions(p: Pattern, cut: tuple[int, ...]) -> list[tuple[Pattern, int]]:
    """Quotients up to isomorphism and how often each arises: all that a count needs."""
    first: dict[tuple, Pattern] = {}
    times: Counter = Counter()
    for c in collisions(p, cut):
        code = canonical_code(c.quotient)
        first.setdefault(code, c.quotient)
        times[code] += 1
    return [(first[k], n) for k, n in times.items()]
