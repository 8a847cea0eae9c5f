"""Named patterns and the list of all connected patterns of a size."""

from __future__ import annotations

from functools import lru_cache
from itertools import combinations, permutations

import numpy as np

from cutloom.patterns.algebra import Pattern, automorphisms, canonical_code


def chain(n: int) -> Pattern:
    return Pattern.of(n, [(i, i + 1) for i in range(n - 1)])


def cycle(n: int) -> Pattern:
    return Pattern.of(n, [(i, (i + 1) % n) for i in range(n)])


def clique(n: int) -> Pattern:
    return Pattern.of(n, combinations(range(n), 2))


def star(leaves: int) -> Pattern:
    return Pattern.of(leaves + 1, [(0, i) for i in range(1, leaves + 1)])


def tailed_triangle() -> Pattern:
    return Pattern.parse("01 02 12 03")


def diamond() -> Pattern:
    return Pattern.parse("01 02 03 12 13")


def house() -> Pattern:
    return Pattern.parse("01 02 03 12 14 34")


@lru_cache(maxsize=16)
def connected_patterns(n: int) -> tuple[Pattern, ...]:
    """All connected patterns of n vertices up to isomorphism, by edges: 1, 2, 6, 21, 112 for n = 2 to 6.

    Every connected pattern has a vertex whose removal leaves it connected, so
    each grows from one of the size below.
    """
    if n == 1:
        return (Pattern.of(1, []),)
    found: dict[tuple, Pattern] = {}
    for smaller in connected_patterns(n - 1):
        for k in range(1, n):
            for near in combinations(range(n - 1), k):
                p = Pattern.of(n, [*smaller.edges, *((v, n - 1) for v in near)])
                found.setdefault(canonical_code(p), p)
    return tuple(sorted(found.values(), key=lambda p: (p.m, canonical_code(p)[2])))


def pseudo_cliques(n: int, k: int = 1) -> tuple[Pattern, ...]:
    """Connected patterns of n vertices that lack at most k edges of a clique."""
    every = list(combinations(range(n), 2))
    found: dict[tuple, Pattern] = {}
    for missing in range(k + 1):
        for gone in combinations(every, missing):
            p = Pattern.of(n, set(every) - set(gone))
            if p.connected():
                found.setdefault(canonical_code(p), p)
    return tuple(found.values())


def _mask(edges, n: int) -> int:
    return sum(1 << (a * n + b) for a, b in edges)


@lru_cache(maxsize=8)
def spanning_coefficients(n: int) -> np.ndarray:
    """c[i, j]: how many edge subsets of pattern j, on all its vertices, are isomorphic to pattern i."""
    patterns = connected_patterns(n)
    out = np.zeros((len(patterns), len(patterns)), np.int64)
    masks = np.array([_mask(p.edges, n) for p in patterns], np.uint64)
    for i, p in enumerate(patterns):
        images = {_mask({(min(g[a], g[b]), max(g[a], g[b])) for a, b in p.edges}, n) for g in permutations(range(n))}
        assert len(images) * len(automorphisms(p)) == np.prod(range(1, n + 1))
        shapes = np.fromiter(images, np.uint64, len(images))
        out[i] = [int(((shapes & ~m) == 0).sum()) for m in masks]
    return out
