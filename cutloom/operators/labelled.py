"""Domains of labelled patterns of up to three edges over neighbour lists that every task holds, in numpy.

No matching of two edges or more is a row.  A vertex fills a role if a fragment
of the pattern is left for the rest: how many neighbours of each label a vertex
has decides it, less the vertices that are taken already.  A task takes every
so-manieth vertex and counts those that fill each role of each tuple of labels.
"""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import functions as F

from cutloom.operators.kernel import ROWS, Lists, hashed

# workers needn't have this package in their path
cloudpickle.register_pickle_by_value(sys.modules[__name__])

#: Cells of a count by vertex and two labels, and tuples of four labels, that a task holds; with more, patterns are mined by joins.
MOST_CELLS, MOST_TUPLES = 1 << 26, 1 << 18
#: Cells of the rows that are looked at together.
TOGETHER = 1 << 20
#: Tables of counts: shape, role and how many labels a tuple has.
TABLES = {"edge 0": 2, "chain3 0": 3, "chain3 1": 3, "triangle 0": 3, "star3 0": 4, "star3 1": 4, "chain4 0": 4, "chain4 2": 4}


class Labelled:
    """Vertices renumbered by (label, place), so a list has the neighbours of a label in one piece; arcs of infrequent pairs of labels are left out."""

    def __init__(self, lists: Lists, label: np.ndarray, kinds: int, at_least: int | None):
        self.k = k = kinds
        order = np.argsort(label, kind="stable")
        order = order[np.searchsorted(label[order], 0):]  # those without a label come first
        new = np.full(lists.n, -1, np.int32)
        new[order] = np.arange(len(order), dtype=np.int32)
        self.n, self.label = len(order), label[order].astype(np.int64)
        src = new[np.repeat(np.arange(lists.n, dtype=np.int32), np.diff(lists.at))]
        near = new[lists.near]
        keep = (src >= 0) & (near >= 0)
        src, near = src[keep], near[keep]
        self.every = self.counted(src, near)
        if at_least is not None:
            found = np.stack([(self.every[self.label == a] > 0).sum(axis=0) for a in range(k)]) if k else np.zeros((0, 0), np.int64)
            frequent = np.minimum(found, found.T) >= at_least
            keep = frequent[self.label[src], self.label[near]]
            src, near = src[keep], near[keep]
        self.count = self.counted(src, near)
        arcs = src.astype(np.int64)
        arcs <<= 32
        arcs |= near
        arcs.sort()
        self.src, near = (arcs >> 32).astype(np.int32), arcs.astype(np.int32)
        del arcs
        self.at = np.searchsorted(self.src, np.arange(self.n + 1))
        #: where the neighbours of each vertex and label begin
        self.begin = np.concatenate([[0], np.cumsum(self.count.ravel())])
        bits = np.zeros(1 << max(3, min(25, len(near).bit_length() + 1)), np.uint8)
        for i in range(0, len(near), ROWS):
            h = hashed(self.src[i: i + ROWS], near[i: i + ROWS], len(bits))
            np.bitwise_or.at(bits, h >> 3, np.uint8(1) << (h & 7).astype(np.uint8))
        self.lists = Lists(order, self.at, near, None, bits)

    def counted(self, src: np.ndarray, near: np.ndarray) -> np.ndarray:
        """How many neighbours of each label a vertex has."""
        return np.bincount(src.astype(np.int64) * self.k + self.label[near], minlength=self.n * self.k).reshape(self.n, self.k).astype(np.int32)

    def tied(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        """Vertices that lost all arcs have no list to be searched."""
        ok = (self.at[u + 1] > self.at[u]) & (self.at[v + 1] > self.at[v])
        out = np.zeros(len(u), bool)
        out[ok] = self.lists.tied(u[ok], v[ok])
        return out

    def seconds(self) -> tuple[np.ndarray, np.ndarray]:
        """(far, sole): how many neighbours of v with label a have a neighbour of label b besides v, and for each arc (v, w)
        and label a how many of those have w as the only one (b is w's label)."""
        k, near = self.k, self.lists.near
        far = np.zeros((self.n * k, k), np.int16 if self.count.max(initial=0) < 1 << 15 else np.int32)
        total = [np.zeros(0, np.int64), np.zeros(0, np.int64)]
        ids = np.bincount(self.src.astype(np.int64) * k + self.label[near], near, minlength=self.n * k).reshape(self.n, k)  # of a sole neighbour: its number
        step = max(1, TOGETHER // k)
        for i in range(0, len(near), step):
            v, x = self.src[i: i + step].astype(np.int64), near[i: i + step]
            left, at = self.count[x], np.arange(len(v))
            left[at, self.label[v]] -= 1
            group = v * k + self.label[x]  # in order
            first = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
            far[group[first]] += np.add.reduceat((left > 0).astype(far.dtype), first, axis=0)
            row, b = np.nonzero(left == 1)
            w = (ids[x[row], b] - np.where(self.label[v[row]] == b, v[row], 0)).astype(np.int64)
            keep = self.tied(v[row], w)
            row, w = row[keep], w[keep]
            arc = self.lists.first(v[row], w) if len(row) else row
            total[0] = np.concatenate([total[0], arc * k + self.label[x[row]]])
        keys, times = np.unique(total[0], return_counts=True)
        return far.reshape(self.n, k, k), np.stack([keys, times])

    def chains(self, far: np.ndarray, sole: np.ndarray, v: np.ndarray, w: np.ndarray, arc: np.ndarray) -> np.ndarray:
        """[a, b] for each arc (v, w): whether v has another neighbour of label a that has one of label b, neither v nor w."""
        k, at = self.k, np.arange(len(v))
        out = far[v].astype(np.int32)
        own = self.count[w]  # w isn't the neighbour itself
        own[at, self.label[v]] -= 1
        out[at, self.label[w]] -= own > 0
        if sole.shape[1] and len(arc):
            key = (arc[:, None] * k + np.arange(k)).ravel()
            place = np.minimum(np.searchsorted(sole[0], key), sole.shape[1] - 1)
            less = np.where(sole[0][place] == key, sole[1][place], 0).reshape(len(v), k)
            out[at, :, self.label[w]] -= less.astype(np.int32)
        return out > 0

    def triangles(self, v: np.ndarray) -> np.ndarray:
        """[a, b] for each vertex: whether it lies in a triangle with vertices of these labels.  More and more neighbours are looked at where none was found."""
        k, near = self.k, self.lists.near
        has = self.count[v] > 0
        out = np.zeros((len(v), k, k), bool)
        row, a, b = np.nonzero(has[:, :, None] & has[:, None, :] & np.tri(k, dtype=bool).T)
        done, upto = 0, 2
        while len(row):
            begin = self.begin[v[row] * k + a]
            size = np.minimum(self.count[v[row], a], upto) - done
            for some in _pieces(size):
                one = np.repeat(some, size[some])
                x = near[begin[one] + done + _places(size[some])].astype(np.int64)
                more = self.count[x, b[one]]
                for part in _pieces(more):
                    y = near[np.repeat(self.begin[x[part] * k + b[one[part]]], more[part]) + _places(more[part])]
                    r = np.repeat(one[part], more[part])
                    r = r[self.tied(v[row[r]], y)]
                    out[row[r], a[r], b[r]] = True
            left = ~out[row, a, b] & (self.count[v[row], a] > upto)
            row, a, b = row[left], a[left], b[left]
            done, upto = upto, 4 * upto
        return out | out.transpose(0, 2, 1)


def _places(size: np.ndarray) -> np.ndarray:
    """0, 1, .. for each size, one after the other."""
    return np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)


def _pieces(size: np.ndarray):
    """Ranges of places whose sizes add up to ROWS, or single ones."""
    sums, done = np.cumsum(size), 0
    while done < len(size):
        upto = max(int(np.searchsorted(sums, (int(sums[done - 1]) if done else 0) + ROWS, "right")), done + 1)
        yield np.arange(done, upto)
        done = upto


def domains(x: Labelled, start: int, step: int, largest: int) -> dict[str, np.ndarray]:
    """The tables of counts, over every so-manieth vertex."""
    k = x.k
    out = {name: np.zeros((k,) * dims, np.int64) for name, dims in TABLES.items()}
    mine = np.arange(start, x.n, step)
    np.add.at(out["edge 0"], x.label[mine], (x.every[mine] > 0).astype(np.int64))
    if largest < 2 or not len(x.src):
        return out
    same, sorts = np.eye(k, dtype=np.int32), np.arange(k)
    triple = 1 + (sorts[:, None, None] == sorts[None, :, None]) + (sorts[:, None, None] == sorts)  # how many of the three have the first one's label
    far, sole = x.seconds() if largest > 2 else (None, None)
    degree = x.at[mine + 1] - x.at[mine]
    sums, done = np.cumsum(degree * k * k + k ** 3), 0
    while done < len(mine):
        upto = max(int(np.searchsorted(sums, (int(sums[done - 1]) if done else 0) + TOGETHER, "right")), done + 1)
        v, own = mine[done:upto], degree[done:upto]
        done = upto
        c = x.count[v]
        pairs = lambda c: (c[:, :, None] > same) & (c[:, None, :] > 0)  # noqa: E731 - two neighbours of these labels
        np.add.at(out["chain3 0"], x.label[v], pairs(c).astype(np.int64))
        arc = np.repeat(x.at[v], own) + _places(own)
        here, there = np.repeat(v, own), x.lists.near[arc].astype(np.int64)
        group = here * k + x.label[there]  # in order
        first = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]])) if len(group) else np.zeros(0, np.int64)
        if len(first):
            at, label = x.label[group[first] // k], group[first] % k
            less = x.count[there]
            less[np.arange(len(there)), x.label[here]] -= 1
            np.add.at(out["chain3 1"], (label, at), np.maximum.reduceat((less > 0).astype(np.int8), first, axis=0).astype(np.int64))
        if largest < 3:
            continue
        np.add.at(out["triangle 0"], x.label[v], x.triangles(v).astype(np.int64))
        for n in range(0, len(v), max(1, TOGETHER // k ** 3)):
            c = x.count[v[n: n + max(1, TOGETHER // k ** 3)]]
            enough = c[:, :, None, None] >= triple  # of the first one's label
            np.add.at(out["star3 0"], x.label[v[n: n + len(c)]], (enough & enough.transpose(0, 2, 1, 3) & enough.transpose(0, 3, 2, 1)).astype(np.int64))
        if len(first):
            np.add.at(out["star3 1"], (label, at), np.maximum.reduceat(pairs(less).astype(np.int8), first, axis=0).astype(np.int64))
            ok = x.chains(far, sole, here, there, arc)  # v in the middle, its leaf there
            leaf = np.maximum.reduceat(ok.astype(np.int8), first, axis=0).astype(np.int64)
            chain = out["chain4 0"].transpose(0, 2, 1, 3)  # (own, leaf's, other middle's, its leaf's)
            np.add.at(chain, (at, label), leaf)
            back = x.lists.first(there, here)
            ok = x.chains(far, sole, there, here, back)  # v is the leaf
            chain = out["chain4 2"].transpose(0, 2, 1, 3)
            np.add.at(chain, (label, at), np.maximum.reduceat(ok.astype(np.int8), first, axis=0).astype(np.int64))
    return out


def supports(g, largest: int, at_least: int | None) -> dict[str, np.ndarray] | None:
    """The support of each shape by labels, with the sorted labels as ``labels``; None where the graph or its labels are too many for a task."""
    if not g.fits() or g.size == 0:
        return None
    spark, wanted = g.spark, g.vertices.where("label IS NOT NULL")
    most = int(MOST_TUPLES ** 0.25)
    names = sorted(r["label"] for r in wanted.select("label").distinct().limit(most + 1).collect())
    lists = g.lists()
    ids = lists.value[0]
    if len(names) > most or len(ids) * len(names) ** 2 > MOST_CELLS:
        return None
    codes = spark.createDataFrame([(x, i) for i, x in enumerate(names)], "label string, code int")
    rows = wanted.join(F.broadcast(codes), "label").select(F.col("v").cast("long").alias("v"), "code").toArrow()
    v, code = rows.column("v").to_numpy(), rows.column("code").to_numpy()
    order = np.argsort(ids)
    at = np.minimum(np.searchsorted(ids, v, sorter=order), len(ids) - 1)
    known = ids[order[at]] == v
    label = np.full(len(ids), -1, np.int32)
    label[order[at[known]]] = code[known]
    labels, kinds, step = spark.sparkContext.broadcast(label), len(names), spark.sparkContext.defaultParallelism

    def run(batches):
        held = None
        for batch in batches:
            for s in batch.column(0).to_pylist():
                held = held or Labelled(Lists(*lists.value), labels.value, kinds, at_least)
                for name, found in domains(held, s, step, largest).items():
                    cells = np.flatnonzero(found)
                    yield pa.RecordBatch.from_pydict({"name": pa.array([name] * len(cells), pa.string()), "cell": pa.array(cells, pa.int64()), "n": pa.array(found.ravel()[cells], pa.int64())})

    found = spark.range(0, step, 1, step).mapInArrow(run, "name string, cell long, n long").groupBy("name", "cell").agg(F.sum("n").alias("n")).toArrow()
    labels.unpersist()
    tables, name = {}, found.column("name").to_numpy(zero_copy_only=False)
    for x, dims in TABLES.items():
        mine = name == x
        flat = np.zeros(kinds ** dims, np.int64)
        flat[found.column("cell").to_numpy()[mine]] = found.column("n").to_numpy()[mine]
        tables[x] = flat.reshape((kinds,) * dims)
    least = lambda table, *turns: np.minimum.reduce([tables[table].transpose(t) for t in turns])
    middle = (0, 1, 2, 3), (1, 0, 3, 2)
    return {
        "labels": np.array(names, object),
        "edge": least("edge 0", (0, 1), (1, 0)),
        "chain3": np.minimum(tables["chain3 0"], least("chain3 1", (0, 1, 2), (0, 2, 1))),
        "triangle": least("triangle 0", (0, 1, 2), (1, 0, 2), (2, 1, 0)),
        "star3": np.minimum(tables["star3 0"], least("star3 1", (0, 1, 2, 3), (0, 2, 1, 3), (0, 3, 2, 1))),
        "chain4": np.minimum(least("chain4 0", *middle), least("chain4 2", *middle)),
    }
