"""Counts over neighbour lists that every task holds, in numpy: no row of a matching leaves its task.

Vertices are numbered by (degree, id), so an edge is looked up in the shorter
of two lists, and what is restricted to rise from a start vertex rises from
light vertices to hubs.  A task takes every so-manieth start vertex.  All parts
of a cut start from one vertex of the cut, so the matches of a cut lie whole in
one task, and a joint count is a sum over tasks.  Levels grow in slices of
bounded size.
"""

from __future__ import annotations

import sys
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutloom.patterns.algebra import Pattern, automorphisms, restrictions

# workers needn't have this package in their path
cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Arcs of the graphs that are sent to every task; larger ones are joined.
MOST_ARCS = 32_000_000
#: Rows that a slice of a level grows to, cells of a table that is held dense, and squares of degrees of the start vertices taken together.
ROWS, CELLS, TOGETHER = 1 << 19, 1 << 22, 1 << 19
#: Cut matches beyond so many possible ones have keys of several numbers.
WIDE = 1 << 62
#: Cut matches that one start vertex may have, by the largest degree; cuts that may have more are joined.
MOST_MATCHES = 1 << 24


def hashed(u: np.ndarray, v: np.ndarray, size: int) -> np.ndarray:
    """A bit's place for each pair, either way round, in so many bytes (a power of two)."""
    a, b = np.minimum(u, v).astype(np.uint64), np.maximum(u, v).astype(np.uint64)
    a *= np.uint64(0x9E3779B97F4A7C15)
    a += b * np.uint64(0xC2B2AE3D27D4EB4F)
    a ^= a >> np.uint64(29)
    a *= np.uint64(0xBF58476D1CE4E5B9)
    return (a >> np.uint64(65 - (8 * size).bit_length())).astype(np.int64)


@dataclass(frozen=True)
class Lists:
    """Vertex i has the neighbours near[at[i]:at[i + 1]], in order; ``ids`` are the graph's own.

    ``left`` marks the sources, where no vertex is a source and a target: then the graph is bipartite.
    ``bits`` has a bit set for the hash of every edge, so most pairs that aren't tied needn't be searched for.
    """

    ids: np.ndarray
    at: np.ndarray
    near: np.ndarray
    left: np.ndarray | None = None
    bits: np.ndarray | None = None

    @property
    def n(self) -> int:
        return len(self.ids)

    @staticmethod
    def of(src: np.ndarray, dst: np.ndarray) -> Lists:
        ids = np.union1d(np.unique(src), np.unique(dst))
        src, dst = (np.searchsorted(ids, x).astype(np.int32) for x in (src, dst))
        ids = ids.astype(np.int64)
        degree = np.bincount(src, minlength=len(ids)) + np.bincount(dst, minlength=len(ids))
        order = np.argsort(degree, kind="stable")
        rank = np.empty(len(ids), np.int32)
        rank[order] = np.arange(len(ids), dtype=np.int32)
        src, dst = rank[src], rank[dst]
        left = np.zeros(len(ids), bool)
        left[src] = True
        left = None if left[dst].any() else left
        m = len(src)
        arcs = np.empty(2 * m, np.int64)
        for one, a, b in ((arcs[:m], src, dst), (arcs[m:], dst, src)):
            one[:] = a
            one <<= 32
            one |= b
        arcs.sort()
        near = arcs.astype(np.int32)  # the low half
        del arcs
        bits = np.zeros(1 << max(3, min(25, (2 * m).bit_length() + 1)), np.uint8)
        for k in range(0, m, ROWS):
            h = hashed(src[k: k + ROWS], dst[k: k + ROWS], len(bits))
            np.bitwise_or.at(bits, h >> 3, np.uint8(1) << (h & 7).astype(np.uint8))
        return Lists(ids[order], np.concatenate([[0], np.cumsum(degree[order])]).astype(np.int64), near, left, bits)

    def first(self, u: np.ndarray, x: np.ndarray) -> np.ndarray:
        """Where the list of each u has its first vertex that isn't below x; every vertex has a neighbour."""
        base = self.at[u]
        length = self.at[u + 1] - base
        for _ in range(int(length.max(initial=1) - 1).bit_length()):
            half = length >> 1
            base += half * (self.near[base + half - 1] < x)
            length -= half
        return base + (self.near[base] < x)

    def tied(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        if self.bits is None:
            return self._found(u, v)
        h = hashed(u, v, len(self.bits))
        out = (self.bits[h >> 3] >> (h & 7).astype(np.uint8)) & 1 == 1
        maybe = np.flatnonzero(out)
        out[maybe] = self._found(u[maybe], v[maybe])
        return out

    def _found(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        a, b = np.minimum(u, v), np.maximum(u, v)
        at = self.first(a, b)
        return (at < self.at[a + 1]) & (self.near[np.minimum(at, len(self.near) - 1)] == b)


@dataclass(frozen=True)
class Walk:
    """An enumeration in an order: for each level the earlier levels it is tied to, those it only differs from, and those it must be above and below.

    ``keys`` are the levels of the cut vertices.  The first ``replay`` levels are
    enumerated once for each embedding, and ``images`` relabel them.
    """

    levels: tuple[tuple[tuple[int, ...], ...], ...]
    keys: tuple[int, ...] = ()
    induced: bool = False
    replay: int = 0
    images: tuple[tuple[int, ...], ...] = ()


def walk(p: Pattern, order: tuple[int, ...], pinned=(), induced: str = "edge", keys: tuple[int, ...] = (), replay: int = 0) -> Walk:
    """The walk of a pattern without labels; ``keys`` are pattern vertices."""
    at = {v: i for i, v in enumerate(order)}
    q = p.induced(list(order))
    own = [(at[a], at[b]) for a, b in pinned]
    images: tuple[tuple[int, ...], ...] = ()
    if replay >= 2:
        head = q.induced(list(range(replay)))
        own, images = restrictions(head), automorphisms(head)
    levels = []
    for i in range(q.n):
        back = tuple(sorted(u for u in q.neighbours[i] if u < i))
        if i and not back:
            raise ValueError("the order isn't connected")
        levels.append((back, tuple(u for u in range(i) if u not in back), tuple(a for a, b in own if b == i and a < i), tuple(b for a, b in own if a == i and b < i)))
    return Walk(tuple(levels), tuple(at[v] for v in keys), induced == "vertex", replay if replay >= 2 else 0, images)


Emit = Callable[[list, "np.ndarray | None"], None]


def grow(lists: Lists, w: Walk, columns: list[np.ndarray], emit: Emit, i: int = 1, replayed: bool = False, whole: bool = False) -> None:
    """Hand the matchings that rows of the first i levels grow into to ``emit``, with how many each row stands for (None: one).

    The last level isn't made, if it is only counted; ``whole`` asks for it.
    """
    if not len(columns[0]):
        return
    if w.replay == i and not replayed:
        for image in w.images:
            grow(lists, w, [columns[k] for k in image], emit, i, True, whole)
        return
    if i == len(w.levels):
        emit(columns, None)
        return
    back, other, low, high = w.levels[i]
    ends = [columns[u] for u in back]
    rest: list[np.ndarray] = []
    if len(ends) > 1:  # from the shortest of the lists that must hold the new vertex
        anchor, *rest = np.sort(np.stack(ends), axis=0)
    else:
        anchor = ends[0]
    begin, end = lists.at[anchor], lists.at[anchor + 1]
    above = np.maximum.reduce([columns[u] for u in low]) if low else None
    below = np.minimum.reduce([columns[u] for u in high]) if high else None
    if above is not None:
        begin = lists.first(anchor, above + 1)
    if below is not None:
        end = lists.first(anchor, below)
    size = np.maximum(end - begin, 0)
    if i == len(w.levels) - 1 and i not in w.keys and not rest and not w.induced and not whole:
        for u in other:
            x = columns[u]
            taken = lists.tied(anchor, x)
            taken &= True if above is None else x > above
            taken &= True if below is None else x < below
            size = size - taken
        emit(columns, size)
        return
    sums = np.cumsum(size)
    done, n = 0, len(size)
    while done < n:
        before = int(sums[done - 1]) if done else 0
        upto = max(int(np.searchsorted(sums, before + ROWS, "right")), done + 1)
        total = int(sums[upto - 1]) - before
        if total:
            own = size[done:upto]
            row = np.repeat(np.arange(done, upto), own)
            new = lists.near[np.arange(total) + np.repeat(begin[done:upto] - (sums[done:upto] - own - before), own)]
            for u in other:
                keep = new != columns[u][row]
                row, new = row[keep], new[keep]
            for x in rest:
                keep = lists.tied(new, x[row])
                row, new = row[keep], new[keep]
            if w.induced:
                for u in other:
                    keep = ~lists.tied(new, columns[u][row])
                    row, new = row[keep], new[keep]
            grow(lists, w, [*(c[row] for c in columns), new], emit, i + 1, replayed, whole)
        done = upto


def total(lists: Lists, w: Walk, roots: np.ndarray) -> int:
    found = [0]

    def emit(columns, weight):
        found[0] += len(columns[0]) if weight is None else int(weight.sum())

    grow(lists, w, [roots], emit)
    return found[0]


def _summed(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    new = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    return keys[new], np.add.reduceat(counts, new) if len(new) else counts[:0]


def table(lists: Lists, w: Walk, roots: np.ndarray, ordered: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(cut matches as keys, in order if ``ordered``; how many matchings each has) of the matchings from ``roots``, which are in order."""
    n, k = lists.n, len(w.keys)
    if (edges := path_edges(w)) and len(roots) * n < WIDE:
        keys, counts = path_counts(lists, roots, edges)
        order = np.argsort(keys) if ordered else slice(None)
        return keys[order], counts[order]
    if w.levels in SQUARES and w == Walk(w.levels, (0,)):  # two of the vertices that are two edges away by both
        keys, counts = path_counts(lists, roots, 2)
        squares = np.bincount(keys // n, counts * (counts - 1.0), minlength=len(roots)).astype(np.int64)
        found = np.flatnonzero(squares)
        return found, squares[found]
    started = 0 in w.keys and not w.replay  # each key has a start vertex
    cells = len(roots) * n ** (k - 1) if started else n ** k

    def key(columns) -> np.ndarray:
        if cells >= WIDE:
            return np.ascontiguousarray(np.stack([columns[i] for i in w.keys], axis=1).astype(">i8")).view(f"V{8 * k}").ravel()
        out = np.zeros(len(columns[0]), np.int64)
        for i in w.keys:
            out = out * len(roots) + np.searchsorted(roots, columns[0]) if started and i == 0 else out * n + columns[i]
        return out

    if cells <= CELLS:
        dense = np.zeros(cells, np.int64)

        def count(columns, weight):
            np.add.at(dense, key(columns), 1 if weight is None else weight)

        grow(lists, w, [roots], count)
        found = np.flatnonzero(dense)
        return found, dense[found]
    held: list[tuple[np.ndarray, np.ndarray]] = []
    size = [0]

    def collect(columns, weight):
        own = _summed(key(columns), np.ones(len(columns[0]), np.int64) if weight is None else weight)
        held.append(own)
        size[0] += len(own[0])
        if size[0] > 4 * ROWS and len(held) > 1 and size[0] > 2 * len(held[0][0]):
            held[:] = [_summed(*map(np.concatenate, zip(*held)))]
            size[0] = len(held[0][0])

    grow(lists, w, [roots], collect)
    keys, counts = _summed(*map(np.concatenate, zip(*held))) if held else (np.zeros(0, np.int64), np.zeros(0, np.int64))
    return keys[counts > 0], counts[counts > 0]


def unpacked(lists: Lists, w: Walk, roots: np.ndarray, keys: np.ndarray) -> list[np.ndarray]:
    """The vertices of a table's cut matches, by the graph's own ids."""
    if keys.dtype.kind == "V":
        return [lists.ids[c] for c in keys.view(">i8").reshape(-1, len(w.keys)).T.astype(np.int64)]
    out = []
    for i in reversed(w.keys):
        root = i == 0 and not w.replay
        keys, at = np.divmod(keys, len(roots) if root else lists.n)
        out.append(lists.ids[roots[at] if root else at])
    return out[::-1]


#: Walks along a path between two keys, of two and of three edges, and the two ways round a square from its key.
PATHS = {edges: tuple(((i - 1,) if i else (), tuple(range(i - 1)), (), ()) for i in range(edges + 1)) for edges in (2, 3)}
SQUARES = {walk(Pattern.parse("01 12 23 03"), order).levels for order in ((0, 1, 2, 3), (0, 1, 3, 2))}


def path_edges(w: Walk) -> int:
    """How many edges the path has that the walk goes along, or 0."""
    return next((k for k, levels in PATHS.items() if w == Walk(levels, (0, k))), 0)


def _merged(keys: np.ndarray, weights: np.ndarray, scratch: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each key once, in no order, and the sum of its weights; ``scratch`` has a cell for each possible key, of any content."""
    own = np.arange(len(keys), dtype=np.int32)
    scratch[keys] = own
    at = scratch[keys]
    first = np.flatnonzero(at == own)
    return keys[first], np.bincount(at, weights, minlength=len(keys))[first]


def _stepped(lists: Lists, keys: np.ndarray, weights: np.ndarray, less: tuple[np.ndarray, np.ndarray], cells: int, scratch: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(root, vertex) pairs as keys, and weights, one edge further; ``less`` is added, its keys differ."""
    at, x = np.divmod(keys, lists.n)
    begin, size = lists.at[x], lists.at[x + 1] - lists.at[x]
    sums, base = np.cumsum(size), at * lists.n

    def made(done: int, upto: int) -> tuple[np.ndarray, np.ndarray]:
        own, before = size[done:upto], int(sums[done - 1]) if done else 0
        new = lists.near[np.arange(int(sums[upto - 1]) - before) + np.repeat(begin[done:upto] - (sums[done:upto] - own - before), own)]
        return new + np.repeat(base[done:upto], own), np.repeat(weights[done:upto], own)

    if not len(sums) or sums[-1] <= 2 * ROWS:
        some = made(0, len(size)) if len(sums) else (keys, weights)
        return _merged(*map(np.concatenate, zip(some, less)), scratch)
    dense, done = np.zeros(cells), 0
    while done < len(size):
        upto = max(int(np.searchsorted(sums, (int(sums[done - 1]) if done else 0) + ROWS, "right")), done + 1)
        np.add.at(dense, *made(done, upto))
        done = upto
    dense[less[0]] += less[1]
    found = np.flatnonzero(dense)
    return found, dense[found]


def path_counts(lists: Lists, roots: np.ndarray, edges: int) -> tuple[np.ndarray, np.ndarray]:
    """(root's place * n + end; paths of 2 or 3 edges between the two), in no order.

    These are all walks but those that come back: to the start of two edges, or, of
    three, over an edge of the start (its degree and the end's, less the walk that
    is counted in both).
    """
    n = lists.n
    step, out = max(1, CELLS // n), []
    scratch = np.empty(min(step, max(len(roots), 1)) * n, np.int32)
    none = np.zeros(0, np.int64), np.zeros(0)
    for k in range(0, len(roots), step):
        some = roots[k: k + step]
        start = np.arange(len(some)) * n + some
        cells = len(some) * n
        near, one = _stepped(lists, start, np.ones(len(some)), none, cells, scratch)
        keys, found = _stepped(lists, near, one, none, cells, scratch)
        if edges == 3:
            at, end = np.divmod(near, n)
            degree = np.diff(lists.at)
            keys, found = _stepped(lists, keys, found, (near, 1.0 - degree[some[at]] - degree[end]), cells, scratch)
        keep = (found > 0) & (keys % n != some[keys // n])
        out.append((keys[keep] + k * n, found[keep].astype(np.int64)))
    return tuple(map(np.concatenate, zip(*out))) if out else (none[0], none[0])


def product_sum(tables: list[tuple[np.ndarray, np.ndarray]]) -> int:
    """The sum over keys that all tables have of the product of their counts, exactly."""
    first, *others = sorted(tables, key=lambda t: len(t[0]))
    if all(t is first for t in others):
        return _powers(first[1], len(tables))
    keys, factors = first[0], [first[1]]
    for other, counts in others:
        if not len(keys) or not len(other):
            return 0
        at = np.minimum(np.searchsorted(other, keys), len(other) - 1)
        same = other[at] == keys
        keys, factors = keys[same], [*(f[same] for f in factors), counts[at[same]]]
    if not len(keys):
        return 0
    return _products(factors)


def _powers(counts: np.ndarray, times: int) -> int:
    return _products([counts] * times) if len(counts) else 0


def _products(factors: list[np.ndarray]) -> int:
    bound = len(factors[0])
    for f in factors:
        bound *= int(f.max())
    if bound >= 1 << 62:
        factors = [f.astype(object) for f in factors]
    out = factors[0]
    for f in factors[1:]:
        out = out * f
    return int(out.sum())


def chunks(lists: Lists, roots: np.ndarray) -> Iterator[np.ndarray]:
    """Start vertices in pieces whose squares of degrees add up to TOGETHER, or single ones."""
    work = np.cumsum((lists.at[roots + 1] - lists.at[roots]) ** 2)
    done = 0
    while done < len(roots):
        upto = max(int(np.searchsorted(work, (work[done - 1] if done else 0) + TOGETHER, "right")), done + 1)
        yield roots[done:upto]
        done = upto


#: A count is one walk; a joint count is a tuple of the walks of its parts, whose keys name the cut vertices in one order, the start first.
Task = Walk | tuple[Walk, ...]


def mirrored(lists: Lists, task: tuple[Walk, ...]) -> bool:
    """Whether every cut match has one end on each side of a bipartite graph and the same value turned round."""
    return lists.left is not None and all(path_edges(w) == 3 for w in task)


def fewer(lists: Lists) -> bool:
    """The side of a bipartite graph that has fewer vertices: whether it's the left."""
    return 2 * int(lists.left.sum()) <= lists.n


def values(lists: Lists, tasks: list[Task], roots: np.ndarray) -> list[int]:
    out = [0] * len(tasks)
    for some in chunks(lists, roots):
        known: dict[tuple, tuple[np.ndarray, np.ndarray]] = {}
        for k, task in enumerate(tasks):
            if isinstance(task, Walk):
                out[k] += total(lists, task, some)
                continue
            ordered, twice = len(set(task)) > 1, mirrored(lists, task)
            for w in task:
                if (w, ordered, twice) not in known:
                    known[w, ordered, twice] = table(lists, w, some[lists.left[some] == fewer(lists)] if twice else some, ordered)
            out[k] += product_sum([known[w, ordered, twice] for w in task]) * (2 if twice else 1)
    return out


def counts(g, tasks: list[Task]) -> list[int]:
    """The values of all tasks in one job; a row for each task of Spark and each value passes the driver."""
    if not tasks or g.size == 0:
        return [0] * len(tasks)
    lists, spark = g.lists(), g.spark
    slices = 4 * spark.sparkContext.defaultParallelism

    def run(batches):
        held = Lists(*lists.value)
        for batch in batches:
            for s in batch.column(0).to_pylist():
                found = values(held, tasks, np.arange(s, held.n, slices, dtype=np.int32))
                yield pa.RecordBatch.from_pydict({"k": pa.array(range(len(tasks)), pa.int32()), "value": pa.array(map(str, found), pa.string())})

    rows = spark.range(0, slices, 1, slices).mapInArrow(run, "k int, value string")
    out = [0] * len(tasks)
    for r in rows.collect():
        out[r["k"]] += int(r["value"])
    return out


def timed(g, walks: list[Walk]) -> list[float]:
    """The seconds that all tasks together take for each walk, in one job; what Spark needs to start a job is no part of them."""
    import time

    lists, spark = g.lists(), g.spark
    slices = 4 * spark.sparkContext.defaultParallelism

    def run(batches):
        near = Lists(*lists.value)
        for batch in batches:
            for s in batch.column(0).to_pylist():
                roots, took = np.arange(s, near.n, slices, dtype=np.int32), []
                for w in walks:
                    began = time.perf_counter()
                    for some in chunks(near, roots):
                        total(near, w, some)
                    took.append(time.perf_counter() - began)
                yield pa.RecordBatch.from_pydict({"k": pa.array(range(len(walks)), pa.int32()), "s": took})

    out = [0.0] * len(walks)
    if walks and g.size:
        for r in spark.range(0, slices, 1, slices).mapInArrow(run, "k int, s double").groupBy("k").agg(F.sum("s").alias("s")).collect():
            out[r["k"]] = r["s"]
    return out


P1, P2, P3, P4, P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def xxhash64(*parts: int | np.ndarray) -> np.ndarray:
    """What Spark's function gives for columns of longs, as arrays, and ints, as numbers."""
    turned = lambda x, k: (x << np.uint64(k)) | (x >> np.uint64(64 - k))
    out = np.full(1, 42, np.uint64)
    for x in parts:
        if isinstance(x, np.ndarray):
            out = turned((out + P5 + np.uint64(8)) ^ (turned(x.astype(np.int64).view(np.uint64) * P2, 31) * P1), 27) * P1 + P4
        else:
            out = turned((out + P5 + np.uint64(4)) ^ (np.full(1, x & 0xFFFFFFFF, np.uint64) * P1), 23) * P2 + P3
        out = (out ^ (out >> np.uint64(33))) * P2
        out = (out ^ (out >> np.uint64(29))) * P3
        out ^= out >> np.uint64(32)
    return out


def sampled(g, orders: list[tuple[tuple[int, ...], ...]], rounds: int, share: float, seed: int) -> list[float]:
    """Sums of the weights of sampled walks (see profile.neighbor_sample), by the same draws; an order has the earlier levels that each level is tied to."""
    lists, spark = g.lists(), g.spark
    slices = spark.sparkContext.defaultParallelism
    draw = lambda *parts: (xxhash64(*parts) >> np.uint64(11)) / float(1 << 53)

    def run(batches):
        near = Lists(*lists.value)
        degree, by_id = np.diff(near.at), np.argsort(near.ids)
        place = np.empty(near.n, np.int64)
        place[by_id] = np.arange(near.n)
        listed = (np.repeat(np.arange(near.n), degree) << 32) | place[near.near]  # neighbours by the graph's own ids
        listed.sort()
        listed = by_id[listed & 0xFFFFFFFF]
        for batch in batches:
            for s in batch.column(0).to_pylist():
                sums = [0.0] * len(orders)
                for roots in chunks(near, np.arange(s, near.n, slices)):
                    u = np.repeat(roots, degree[roots])
                    v = near.near[np.arange(len(u)) + np.repeat(near.at[roots] - np.cumsum(degree[roots]) + degree[roots], degree[roots])].astype(np.int64)
                    for t in range(1, rounds + 1):
                        begun = draw(seed, near.ids[u], near.ids[v], t) < share
                        first, second = u[begun], v[begun]
                        key = xxhash64(seed + 7, near.ids[first], near.ids[second], t).view(np.int64)
                        for k, levels in enumerate(orders):
                            columns, weight, own = [first, second], np.ones(len(first)), key
                            for i in range(2, len(levels)):
                                anchor = columns[levels[i][-1]]
                                new = listed[near.at[anchor] + np.floor(draw(seed, own, i) * degree[anchor]).astype(np.int64)]
                                keep = np.ones(len(new), bool)
                                for x in range(i):
                                    if x not in levels[i]:
                                        keep &= columns[x] != new
                                for x in levels[i][:-1]:
                                    keep[keep] = near.tied(columns[x][keep], new[keep])
                                weight = (weight * degree[anchor])[keep]
                                columns, own = [c[keep] for c in (*columns, new)], own[keep]
                            sums[k] += float(weight.sum())
                yield pa.RecordBatch.from_pydict({"k": pa.array(range(len(orders)), pa.int32()), "s": sums})

    out = [0.0] * len(orders)
    for r in spark.range(0, slices, 1, slices).mapInArrow(run, "k int, s double").collect():
        out[r["k"]] += r["s"]
    return out


def sets(lists: Lists, k: int, columns: list[np.ndarray], ties: np.ndarray, emit: Callable[[np.ndarray], None]) -> None:
    """Hand the ties, a bit for each pair (i, j < i) in order, of the connected sets of k vertices that rows of vertices grow into to ``emit``.

    A set is grown once: from its first vertex, each next one is above the first
    and all that come after the one it is found by, and not tied to what comes
    before that one.
    """
    i = len(columns)
    if i == k:
        emit(ties)
        return
    for j in range(i):
        anchor = columns[j]
        begin = lists.first(anchor, np.maximum.reduce([columns[0], *columns[j + 1:]]) + 1)
        size = lists.at[anchor + 1] - begin
        sums, done = np.cumsum(size), 0
        while done < len(size):
            before = int(sums[done - 1]) if done else 0
            upto = max(int(np.searchsorted(sums, before + ROWS, "right")), done + 1)
            own = size[done:upto]
            row = np.repeat(np.arange(done, upto), own)
            new = lists.near[np.arange(int(sums[upto - 1]) - before) + np.repeat(begin[done:upto] - (sums[done:upto] - own - before), own)]
            for u in range(j):
                keep = new != columns[u][row]
                row, new = row[keep], new[keep]
                keep = ~lists.tied(new, columns[u][row])
                row, new = row[keep], new[keep]
            more = ties[row] | 1 << i * (i - 1) // 2 + j
            for u in range(j + 1, i):
                more |= lists.tied(new, columns[u][row]).astype(np.int64) << i * (i - 1) // 2 + u
            if len(new):
                sets(lists, k, [*(c[row] for c in columns), new], more, emit)
            done = upto


def set_shapes(g, k: int) -> DataFrame:
    """(mask, c): how many connected sets of k vertices have the ties of a mask, bit i * k + j for vertices i and j."""
    lists, spark = g.lists(), g.spark
    slices = 4 * spark.sparkContext.defaultParallelism

    def run(batches):
        near, found = Lists(*lists.value), np.zeros(1 << k * (k - 1) // 2, np.int64)

        def emit(ties):
            found[:] += np.bincount(ties, minlength=len(found))

        for batch in batches:
            for s in batch.column(0).to_pylist():
                for some in chunks(near, np.arange(s, near.n, slices, dtype=np.int32)):
                    sets(near, k, [some], np.zeros(len(some), np.int64), emit)
        seen = np.flatnonzero(found)
        masks = sum(((seen >> i * (i - 1) // 2 + j) & 1) * ((1 << i * k + j) | (1 << j * k + i)) for i in range(k) for j in range(i))
        yield pa.RecordBatch.from_pydict({"mask": pa.array(masks, pa.int64()), "c": pa.array(found[seen], pa.int64())})

    return spark.range(0, slices, 1, slices).mapInArrow(run, "mask long, c long").groupBy("mask").agg(F.sum("c").alias("c"))


def part_table(g, q: Pattern, k: int, order: tuple[int, ...], name: str, replay: int = 0) -> DataFrame:
    """(m0 .. m(k-1), count): a part's matchings by its first k vertices, the cut, enumerated in the order given."""
    lists, spark, w = g.lists(), g.spark, walk(q, order, keys=tuple(range(k)), replay=replay)
    names = [f"m{i}" for i in range(k)]
    slices = 4 * spark.sparkContext.defaultParallelism

    def run(batches):
        near = Lists(*lists.value)
        for batch in batches:
            for s in batch.column(0).to_pylist():
                for some in chunks(near, np.arange(s, near.n, slices, dtype=np.int32)):
                    keys, found = table(near, w, some)
                    cut = unpacked(near, w, some, keys)
                    for x in range(0, len(found), 1 << 16):
                        yield pa.RecordBatch.from_arrays([pa.array(c[x: x + (1 << 16)]) for c in (*cut, found)], [*names, name])

    columns = ", ".join(f"{x} long" for x in (*names, name))
    if g.size == 0:
        return spark.createDataFrame([], columns)
    out = spark.range(0, slices, 1, slices).mapInArrow(run, columns)
    return out if 0 in w.keys and not w.replay else out.groupBy(*names).agg(F.sum(name).alias(name))


def rows(g, p: Pattern, order: tuple[int, ...], pinned=(), induced: str = "edge", further: Walk | None = None) -> DataFrame:
    """(m0 .. m(n-1)): the matchings themselves; ``pinned`` holds for the order of (degree, id).

    With ``further``, a walk that starts with this one's levels, a column ``more``
    adds up to how many matchings of that one they grow into, in no certain rows.
    """
    lists, spark, w = g.lists(), g.spark, walk(p, order, pinned, induced)
    names = [f"m{v}" for v in order]
    every = names if further is None else [*names, "more"]
    slices = 4 * spark.sparkContext.defaultParallelism

    def run(batches):
        near = Lists(*lists.value)
        for batch in batches:
            for s in batch.column(0).to_pylist():
                for some in chunks(near, np.arange(s, near.n, slices, dtype=np.int32)):
                    for root in np.array_split(some, max(1, len(some) // 64)):
                        held: list[pa.RecordBatch] = []

                        def made(columns, _, held=held):
                            own = [pa.array(near.ids[c]) for c in columns]
                            if further is not None:
                                grown = np.zeros(len(columns[0]), np.int64)
                                grow(near, further, columns, lambda more, weight: grown.__setitem__(0, grown[0] + (len(more[0]) if weight is None else int(weight.sum()))), len(columns))
                                own.append(pa.array(grown))
                            held.append(pa.RecordBatch.from_arrays(own, every))

                        grow(near, w, [root], made, whole=True)
                        yield from held

    wanted = [*(f"m{v}" for v in range(p.n)), *every[len(names):]]
    if g.size == 0:
        return spark.createDataFrame([], ", ".join(f"{x} long" for x in wanted))
    found = spark.range(0, slices, 1, slices).mapInArrow(run, ", ".join(f"{x} long" for x in every))
    return found.select(*wanted)
