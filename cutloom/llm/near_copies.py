"""Near copies by SimHash and exact shingle similarity; MinHash bands widen the candidates.

How groups are found.  Documents of equal shingle sets are one class.  Classes
whose SimHash fingerprints differ in at most ``RADIUS`` bits are candidates,
found by op4's vantage-point trees.  Of pairs of a similarity of 0.8 most differ
in more bits, so a class also has ``BANDS`` keys, each made of ``ROWS`` minima of
linear permutations of its shingles, and classes that share a key are candidates
too.  The components of all candidates are groups that hold every link found.  Each map task first joins
the classes of a key that it holds itself, so a key of a third of all classes
is shuffled as a few rows for each task.

A group of up to ``GROUP`` shingles meets in one task, which walks it breadth
first and links exactly the pairs of similarity 0.8 or more; a walked document
looks only at those not yet reached.  A larger group is cut into size bands
(sets of a similarity of 0.8 lie in the same band or in neighbours) and blocks
of about ``BLOCK`` shingles.  All its blocks first look at a few pivots of the
bands around them; then the blocks meet in pairs, but for blocks that the
pivots have joined already.  So no task holds more than two blocks, a group of
near copies of one text costs about one look each, and no pair is left out.

A pair of similarity s shares a key with probability 1 - (1 - s^7)^40: 0.9999
at 0.8.  What the bands miss is the only loss; no pair below 0.8 is linked.

Defined results: texts without words have the empty set and are copies of each
other; repeated rows are one class; rows with a null id have no component.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutloom.llm.common import gathered, joined_hot, mix, reliable, shuffle_partitions, text_bytes
from cutloom.llm.simhash import _lower_ascii, components, near_pairs, one_of_each, shingle_hashes, simhash

#: Bits in which fingerprints of candidates differ at most; MinHash bands and the minima of each.
RADIUS = 4
BANDS, ROWS = 40, 7
#: Similarity as a fraction.
LEAST = (4, 5)
#: Shingles of a group that one task takes whole, shingles of a block of a larger group, pivots of a band.
GROUP, BLOCK, PIVOTS = 1 << 18, 1 << 17, 8
#: Ratio of the sizes of a band; sizes of linked sets differ by a factor of 5/4 at most.
BAND_RATIO = 1.3
_rng = np.random.default_rng(20240612)
_FACTORS = _rng.integers(0, 1 << 31, BANDS * ROWS, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_SHIFTS = _rng.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint32)
_WEIGHTS = _rng.integers(0, 1 << 63, (BANDS, ROWS), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_TAGS = _rng.integers(0, 1 << 63, BANDS, dtype=np.uint64)


def shingle_sets(texts: pa.Array, size: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    data, offsets = text_bytes(texts)
    data, bounds = _lower_ascii(data).tobytes(), offsets.tolist()
    for a, b in zip(bounds, bounds[1:]):
        yield np.unique(shingle_hashes(data[a:b], size))


def band_keys(hashes: np.ndarray) -> np.ndarray:
    """BANDS keys of a set; none for the empty set."""
    if not len(hashes):
        return np.zeros(0, np.int64)
    x = (hashes >> np.uint64(32)).astype(np.uint32)
    least = np.full(BANDS * ROWS, 0xFFFFFFFF, np.uint32)
    for i in range(0, len(x), 2048):
        np.minimum(least, (_FACTORS[:, None] * x[i: i + 2048] + _SHIFTS[:, None]).min(axis=1), out=least)
    mixed = (least.reshape(BANDS, ROWS).astype(np.uint64) + np.uint64(1)) * _WEIGHTS
    mixed ^= mixed >> np.uint64(29)
    keys = (mixed * np.uint64(0xFF51AFD7ED558CCD)).sum(axis=1, dtype=np.uint64) + _TAGS
    return (keys ^ (keys >> np.uint64(32))).view(np.int64)


def sketches(docs: DataFrame, size: int, id_col: str, text_col: str) -> DataFrame:
    """(id, cls, fp, keys, size) for each row; cls names the shingle set by 128 bits, fp is its SimHash."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in gathered(batches, 4 << 20):
            sets = list(shingle_sets(rows.column("text"), size))
            cls = pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary())
            fps = np.array([simhash(s) for s in sets], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([rows.column("id").combine_chunks(), cls, pa.array(fps), pa.array([band_keys(s) for s in sets], pa.list_(pa.int64())), pa.array([len(s) for s in sets], pa.int64())], ["id", "cls", "fp", "keys", "size"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(run, "id long, cls binary, fp long, keys array<long>, size long")


def fingerprint_links(classes: DataFrame) -> DataFrame:
    """Links (a, b) of classes (first, fp, ..) whose closure is that of all pairs within RADIUS bits."""
    prints = reliable(classes.groupBy("fp").agg(F.min("first").alias("id"), F.count(F.lit(1)).alias("n")))
    equal = joined_hot(classes.select("fp", "first"), prints, "fp", classes.count()).where("first <> id")
    return near_pairs(prints.select("fp", "id"), RADIUS).unionByName(equal.select(F.col("first").alias("a"), F.col("id").alias("b")))


def band_links(classes: DataFrame) -> DataFrame:
    """Links (a, b) of classes (first, keys, ..) that join all those of a key."""
    shared = classes.select("first", "keys").mapInArrow(_local_stars, "key long, node long")
    least = F.min("node").over(Window.partitionBy("key").orderBy("node").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return shared.withColumn("low", least).select(F.col("node").alias("a"), F.col("low").alias("b"))


def similar_links(nodes: list[int], sets: list[np.ndarray]) -> list[tuple[int, int]]:
    """Links of a spanning forest of all pairs of similarity LEAST or more."""
    up, down = LEAST
    order = sorted(range(len(sets)), key=lambda i: len(sets[i]))
    nodes, sets = [nodes[i] for i in order], [sets[i] for i in order]
    tokens, flat = np.unique(np.concatenate(sets), return_inverse=True)
    sizes = np.array([len(s) for s in sets])
    own = np.split(flat, np.cumsum(sizes)[:-1])
    mark, open_, links = np.zeros(len(tokens), np.int32), np.arange(len(sets)), []
    flat, starts = flat.ravel(), np.concatenate(([0], np.cumsum(sizes)))
    while len(open_):
        work, open_, stale = [int(open_[0])], open_[1:], True
        while work and len(open_):
            i = work.pop()
            if stale:
                flat = np.concatenate([own[j] for j in open_])
                starts, stale = np.concatenate(([0], np.cumsum(sizes[open_]))), False
            low, high = np.searchsorted(sizes[open_], [-(-up * sizes[i] // down), down * sizes[i] // up + 1])
            if low >= high:
                continue
            mark[own[i]] = 1
            common = np.add.reduceat(mark[flat[starts[low]: starts[high]]], starts[low:high] - starts[low])
            mark[own[i]] = 0
            near = np.flatnonzero((up + down) * common >= up * (sizes[i] + sizes[open_[low:high]])) + low
            if len(near):
                reached = open_[near].tolist()
                links += [(nodes[i], nodes[j]) for j in reached]
                work += reached
                open_, stale = np.delete(open_, near), True
    return links


def _local_stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow over (first, keys): (key, node) whose keys join the same nodes, with one row here for each key.

    Of the nodes that share a key in this piece only the least keeps it; each
    other one meets the least under a key of their own.
    """
    def flush() -> pa.RecordBatch:
        keys, nodes = np.concatenate([k for k, _ in held]), np.concatenate([n for _, n in held])
        order = np.lexsort((nodes, keys))
        keys, nodes = keys[order], nodes[order]
        lead = np.ones(len(keys), bool)
        lead[1:] = keys[1:] != keys[:-1]
        least = nodes[np.maximum.accumulate(np.where(lead, np.arange(len(keys)), 0))] if len(keys) else nodes
        apart = ~lead & (nodes != least)
        own = mix(keys[apart].view(np.uint64) ^ mix(nodes[apart].view(np.uint64) ^ mix(least[apart].view(np.uint64)))).view(np.int64)
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate([keys[lead], own, own])), pa.array(np.concatenate([nodes[lead], nodes[apart], least[apart]]))], ["key", "node"])

    held, total = [], 0
    for batch in batches:
        column = batch.column("keys")
        keys = np.asarray(column.flatten(), np.int64)
        held.append((keys, np.repeat(np.asarray(batch.column("first"), np.int64), np.diff(np.asarray(column.offsets)))))
        total += len(keys)
        if total > 1 << 21:
            yield flush()
            held, total = [], 0
    if held:
        yield flush()


def _sets_of(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[tuple[int, bool, int, np.ndarray]]:
    """(unit, pivot, node, set) of each row (unit, pivot, node, text) that has a word."""
    for rows in gathered(batches, 4 << 20):
        units, pivots, nodes = (rows.column(c).to_pylist() for c in ("unit", "pivot", "node"))
        for u, p, n, s in zip(units, pivots, nodes, shingle_sets(rows.column("text"), size)):
            if len(s):
                yield u, p, n, s


def _as_links(found: list[tuple[int, int]]) -> pa.RecordBatch:
    found = [(a, b) for a, b in found if a != b]
    return pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.int64()) for k in (0, 1)], ["a", "b"])


def _unit_links(size: int):
    """mapInArrow over rows sorted by unit: links that span the similar sets of each unit."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unit, held = None, {}
        for u, _, n, s in _sets_of(batches, size):
            if u != unit:
                if len(held) > 1:
                    yield _as_links(similar_links([k[0] for k in held], list(held.values())))
                unit, held = u, {}
            held[n, s.tobytes() if len(s) < 64 else xxhash.xxh3_128_digest(s.tobytes())] = s
        if len(held) > 1:
            yield _as_links(similar_links([k[0] for k in held], list(held.values())))

    return run


def _pivot_links(size: int):
    """mapInArrow over rows sorted by unit, pivots first: each row's links to the pivots of its unit; rows pass one at a time."""
    up, down = LEAST

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unit, found, ready = None, [], False
        for u, p, n, s in _sets_of(batches, size):
            if u != unit:
                unit, nodes, sets, ready = u, [], [], False
            if p:
                nodes.append(n)
                sets.append(s)
                continue
            if not nodes:
                continue
            if not ready:
                sizes = np.array([len(x) for x in sets])
                tokens, owners = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
                order = np.argsort(tokens, kind="stable")
                tokens, owners, ready = tokens[order], owners[order], True
            low, high = np.searchsorted(tokens, s, "left"), np.searchsorted(tokens, s, "right")
            hits = high - low
            at = np.repeat(low - np.cumsum(hits) + hits, hits) + np.arange(int(hits.sum()))
            common = np.bincount(owners[at], minlength=len(sets))
            found += [(n, nodes[i]) for i in np.flatnonzero((up + down) * common >= up * (sizes + len(s))).tolist()]
            if len(found) > 1 << 16:
                yield _as_links(found)
                found = []
        yield _as_links(found)

    return run


def _met(rows: DataFrame, run) -> DataFrame:
    """Links (a, b) found by ``run`` where all rows (unit, pivot, node, text) of a unit meet."""
    return rows.select("unit", "pivot", "node", "text").repartition(shuffle_partitions(rows.sparkSession), "unit").sortWithinPartitions("unit", F.desc("pivot")).mapInArrow(run, "a long, b long")


def _large_links(members: DataFrame, texts: DataFrame, size: int, block: int, pivots: int) -> DataFrame:
    """Links of groups too large for one task; ``members`` are (root, node, size, total), with the shingles of the whole group."""
    band = F.floor(F.log(F.col("size").cast("double")) / F.log(F.lit(BAND_RATIO)))
    members = reliable(members.where("size > 0").withColumn("band", band))
    deal = lambda n: F.pmod(F.xxhash64("node"), F.greatest(F.lit(1), n))
    blocks = F.ceil(F.col("total") / block)
    # the pivots of a band: a few nodes by hash, fewer where sets are long, one at least
    rank = F.row_number().over(Window.partitionBy("root", "band").orderBy(F.xxhash64("node"), "node"))
    chosen = members.withColumn("rank", rank).where(F.col("rank") <= pivots).where(F.expr(f"rank = 1 or rank * size <= {block}"))
    sent = chosen.select("root", F.explode(F.sequence(F.col("band") - 1, F.col("band") + 1)).alias("band"), "node", blocks.alias("blocks")).withColumn("block", F.explode(F.expr("sequence(0L, blocks - 1)")))
    unit = F.xxhash64("root", "band", "block").alias("unit")
    rows = members.withColumn("block", deal(blocks)).select("node", unit, F.lit(False).alias("pivot")).unionByName(sent.select("node", unit, F.lit(True).alias("pivot")))
    first = reliable(_met(rows.join(texts, "node"), _pivot_links(size)))
    # blocks of sets that the pivots joined, and of the others
    labelled = members.join(components(first).select("node", F.col("root").alias("label")), "node", "left").withColumn("known", F.col("label").isNotNull()).withColumn("label", F.coalesce("label", F.lit(0)))
    labelled = reliable(labelled.select("root", "band", "known", "label", "node", "size"))
    kind = ["root", "band", "known", "label"]
    kinds = labelled.groupBy(*kind).agg(F.ceil(F.sum("size") / block).alias("blocks"), F.count(F.lit(1)).alias("n")).withColumn("kind", F.xxhash64(*kind))
    kinds = reliable(kinds)
    x, y = kinds.alias("x"), kinds.alias("y")
    ordered = "x.root = y.root and x.kind <= y.kind and abs(x.band - y.band) <= 1 and not (x.known and y.known and x.label = y.label)"
    pairs = x.join(y, F.expr(ordered)).select(F.col("x.kind").alias("kx"), F.col("y.kind").alias("ky"), F.expr("explode(sequence(0L, x.blocks - 1))").alias("bx"), F.col("y.blocks").alias("by_of"))
    pairs = pairs.select("kx", "ky", "bx", F.expr("explode(sequence(0L, by_of - 1))").alias("by")).where("kx <> ky or bx <= by").withColumn("unit", F.xxhash64("kx", "ky", "bx", "by"))
    cells = pairs.select(F.col("kx").alias("kind"), F.col("bx").alias("block"), "unit").union(pairs.select(F.col("ky").alias("kind"), F.col("by").alias("block"), "unit")).distinct()
    placed = joined_hot(labelled.withColumn("kind", F.xxhash64(*kind)).select("kind", "node"), kinds.select("kind", "blocks", "n"), "kind", labelled.count())
    placed = placed.select("kind", "node", deal(F.col("blocks")).alias("block"))
    second = _met(placed.join(cells, ["kind", "block"]).select("unit", F.lit(False).alias("pivot"), "node").join(texts, "node"), _unit_links(size))
    return first.unionByName(second)


def near_copies(docs: DataFrame, size: int = 5, id_col: str = "doc_id", text_col: str = "text", group: int = GROUP, block: int = BLOCK, pivots: int = PIVOTS, candidates=(fingerprint_links, band_links)) -> DataFrame:
    """(id, component) for each row; component is the smallest id reachable over pairs of similarity 0.8 or more."""
    marked = reliable(sketches(docs, size, id_col, text_col))
    classes = marked.where("id is not null").groupBy("cls").agg(F.min(F.struct("id", "fp", "keys", "size")).alias("m"), F.count(F.lit(1)).alias("n")).select("cls", F.col("m.id").alias("first"), "m.fp", "m.keys", "m.size", "n")
    groups = components(reduce(DataFrame.unionByName, [links(classes) for links in candidates]))
    members = groups.unionByName(groups.select(F.col("root").alias("node"), "root").distinct())
    members = reliable(members.join(classes.select(F.col("first").alias("node"), "size").groupBy("node").agg(F.max("size").alias("size")), "node"))
    totals = members.groupBy("root").agg(F.sum("size").alias("total"), F.count(F.lit(1)).alias("n"))
    members = joined_hot(members, totals, "root", members.count())
    texts = docs.select(F.col(id_col).cast("long").alias("node"), F.col(text_col).alias("text"))
    small = members.where(F.col("total") <= group).select("node", F.col("root").alias("unit"), F.lit(False).alias("pivot"))
    links = _met(small.join(texts, "node"), _unit_links(size))
    large = members.where(F.col("total") > group)
    if not large.isEmpty():
        links = links.unionByName(_large_links(large, texts, size, block, pivots))
    roots = components(links)
    named = classes.select("cls", "first", "n").join(roots, F.col("first") == F.col("node"), "left").select("cls", F.coalesce("root", "first").alias("component"), "n")
    return joined_hot(marked.select("id", "cls"), named, "cls", marked.count()).select("id", F.when(F.col("id").isNotNull(), F.col("component")).alias("component"))


def deduplicated(docs: DataFrame, size: int = 5) -> DataFrame:
    """The rows of ``docs`` with one row for each group of near copies: that of the smallest id."""
    return one_of_each(docs, near_copies(docs, size))
