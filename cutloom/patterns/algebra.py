"""Isomorphism codes, automorphisms and symmetry restrictions of patterns."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property, lru_cache
from itertools import permutations, product


@dataclass(frozen=True)
class Pattern:
    """Vertices 0 to n - 1; ``edges`` are pairs (a, b), a < b; ``labels`` gives each vertex a label or None."""

    n: int
    edges: frozenset[tuple[int, int]]
    labels: tuple | None = None

    @staticmethod
    def of(n: int, edges, labels=None) -> Pattern:
        return Pattern(n, frozenset((min(a, b), max(a, b)) for a, b in edges), None if labels is None else tuple(labels))

    @staticmethod
    def parse(text: str, labels=None) -> Pattern:
        """From vertex pairs such as ``01 02 12``."""
        pairs = [(int(x[0]), int(x[1])) for x in text.split()]
        return Pattern.of(1 + max(max(p) for p in pairs), pairs, labels)

    @cached_property
    def neighbours(self) -> tuple[frozenset[int], ...]:
        near: list[set[int]] = [set() for _ in range(self.n)]
        for a, b in self.edges:
            near[a].add(b)
            near[b].add(a)
        return tuple(map(frozenset, near))

    def adjacent(self, a: int, b: int) -> bool:
        return b in self.neighbours[a]

    def label(self, v: int):
        return None if self.labels is None else self.labels[v]

    @property
    def m(self) -> int:
        return len(self.edges)

    @cached_property
    def name(self) -> str:
        return " ".join(f"{a}{b}" for a, b in sorted(self.edges))

    def components(self, without: frozenset[int] = frozenset()) -> list[frozenset[int]]:
        """Connected components of the pattern less some vertices, by smallest vertex."""
        left, out = set(range(self.n)) - without, []
        while left:
            todo, seen = [min(left)], set()
            while todo:
                v = todo.pop()
                if v not in seen:
                    seen.add(v)
                    todo += self.neighbours[v] & left
            left -= seen
            out.append(frozenset(seen))
        return out

    def connected(self) -> bool:
        return self.n > 0 and len(self.components()) == 1

    def induced(self, keep: list[int]) -> Pattern:
        """The sub-pattern on ``keep``, renumbered in that order."""
        at = {v: i for i, v in enumerate(keep)}
        return Pattern.of(len(keep), [(at[a], at[b]) for a, b in self.edges if a in at and b in at], None if self.labels is None else [self.labels[v] for v in keep])

    def glued(self, block_of: list[int]) -> Pattern:
        """The quotient in which vertices of one block are one vertex; edges are deduplicated."""
        labels = None
        if self.labels is not None:
            labels = [None] * (max(block_of) + 1)
            for v, b in enumerate(block_of):
                labels[b] = labels[b] if self.labels[v] is None else self.labels[v]
        return Pattern.of(max(block_of) + 1, {(min(block_of[a], block_of[b]), max(block_of[a], block_of[b])) for a, b in self.edges}, labels)

    def is_clique(self) -> bool:
        return self.m == self.n * (self.n - 1) // 2


def _colours(p: Pattern, extra: tuple | None = None) -> list:
    """Vertex invariants refined by those of the neighbours, until stable."""
    colour = [(str(p.label(v)), len(p.neighbours[v]), None if extra is None else extra[v]) for v in range(p.n)]
    for _ in range(p.n):
        rank = {c: i for i, c in enumerate(sorted(set(colour), key=repr))}
        finer = [(rank[colour[v]], tuple(sorted(rank[colour[u]] for u in p.neighbours[v]))) for v in range(p.n)]
        if len(set(finer)) == len(set(colour)):
            break
        colour = finer
    return colour


@lru_cache(maxsize=200_000)
def canonical_code(p: Pattern, fixed: tuple | None = None) -> tuple:
    """Equal for isomorphic patterns alone; ``fixed`` gives vertices marks that a map must keep."""
    colour = _colours(p, fixed)
    groups: dict = {}
    for v in range(p.n):
        groups.setdefault(colour[v], []).append(v)
    keys = sorted(groups, key=repr)
    best = None
    for choice in product(*[permutations(groups[k]) for k in keys]):
        order = [v for part in choice for v in part]
        at = {v: i for i, v in enumerate(order)}
        code = tuple(sorted((min(at[a], at[b]), max(at[a], at[b])) for a, b in p.edges))
        best = code if best is None or code < best else best
    marks = tuple((str(p.label(v)), None if fixed is None else fixed[v]) for k in keys for v in groups[k][:1] for _ in groups[k])
    return p.n, marks, best


@lru_cache(maxsize=50_000)
def automorphisms(p: Pattern, fixed: tuple | None = None) -> tuple[tuple[int, ...], ...]:
    """All maps of the pattern on itself that keep edges, labels and marks."""
    colour = _colours(p, fixed)
    out: list[tuple[int, ...]] = []

    def grow(images: list[int]) -> None:
        v = len(images)
        if v == p.n:
            out.append(tuple(images))
            return
        for w in range(p.n):
            if w not in images and colour[w] == colour[v] and all(p.adjacent(w, images[u]) == p.adjacent(v, u) for u in range(v)):
                grow([*images, w])

    grow([])
    return tuple(out)


def orbits(p: Pattern, group: tuple[tuple[int, ...], ...] | None = None) -> list[frozenset[int]]:
    group = automorphisms(p) if group is None else group
    return sorted({frozenset(g[v] for g in group) for v in range(p.n)}, key=min)


def _narrowed(p: Pattern, group, choose) -> Iterator[list[tuple[int, int]]]:
    if len(group) == 1:
        yield []
        return
    moved = [o for o in orbits(p, group) if len(o) > 1]
    for v in choose(moved):
        orbit = next(o for o in moved if v in o)
        own = [(v, u) for u in sorted(orbit - {v})]
        for rest in _narrowed(p, tuple(g for g in group if g[v] == v), choose):
            yield own + rest


def restrictions(p: Pattern) -> list[tuple[int, int]]:
    """Pairs (a, b): the image of a must be smaller than that of b; one matching of each embedding is left."""
    def largest(moved: list[frozenset[int]]) -> list[int]:
        top = max(map(len, moved))
        return [min(min(o) for o in moved if len(o) == top)]

    return next(_narrowed(p, automorphisms(p), largest))


def restriction_sets(p: Pattern, most: int = 64) -> list[list[tuple[int, int]]]:
    """Alternative complete restriction sets, one for each way to pick the vertices that are pinned."""
    out: list[list[tuple[int, int]]] = []
    for found in _narrowed(p, automorphisms(p), lambda moved: sorted(v for o in moved for v in o)):
        if sorted(found) not in [sorted(x) for x in out]:
            out.append(found)
        if len(out) >= most:
            break
    return out
