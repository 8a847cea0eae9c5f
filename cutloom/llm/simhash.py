"""SimHash near-duplicates through vantage-point trees.

``fingerprints`` gives each document 64 bits; ``near_pairs`` links distinct
fingerprints exactly; ``components`` joins links into groups.

How pairs are found.  Two fingerprints at distance 4 or less differ in at most
one bit of their first quarter or agree in one of the three others (else they
would differ in 2 + 1 + 1 + 1 bits), so each quarter is searched with its own
small radius, where the triangle inequality prunes far more.  For each quarter a
vantage-point tree is grown on a sample of at most ``SAMPLE`` distinct
fingerprints, down to shards of about ``SHARD`` members; every fingerprint goes
down all trees, by its Hamming distance to the vantage points, into the one
shard that is its home and, as a visitor, into each shard whose boundary lies
within the tree's radius.  In the first quarter's tree those are the homes of
the 17 values within a bit of its own, so 17 at most however many shards there
are, and in the others none, until values repeat and whole fingerprints are cut:
rows grow with the fingerprints, not with a power of them.  A shard grows its
own tree over its members and sends all visitors down it; a branch is visited
only where the triangle bound lets it hold a partner, and leaves compare whole
fingerprints.  A pair is met in the home shard of either end, so none is lost.  Shards report spanning forests of their links, which keep
connectivity; so a group of thousands of near copies yields links in proportion
to its members.

Defined results: null or empty texts and texts without words have fingerprint
zero and link like any other; repeated rows share their fingerprint; rows with
a null id get a fingerprint but no component (null); a very long text is
fingerprinted whole; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cutloom.llm.common import gathered, joined_hot, reliable, shuffle_partitions, text_bytes

SEED = 42


def _lower_ascii(data: np.ndarray) -> np.ndarray:
    return np.where((data >= 65) & (data <= 90), data + 32, data).astype(np.uint8)


def shingle_hashes(text: bytes, size: int) -> np.ndarray:
    """XXH64 of each shingle of ``size`` words; of the whole sequence if it is shorter."""
    words = text.split()  # bytes.split() separates at exactly \x20 and \x09-\x0D
    if not words:
        return np.zeros(0, np.uint64)
    joined = b" ".join(words)
    if len(words) <= size:
        return np.array([xxhash.xxh64_intdigest(joined, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words))) + np.arange(len(words))
    starts = np.concatenate(([0], ends[: -size] + 1))
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(joined[a:b], SEED) for a, b in zip(starts.tolist(), ends[size - 1:].tolist(), strict=True)), np.uint64, len(starts))


def simhash(hashes: np.ndarray) -> int:
    """A bit is set where more than half the hashes have it."""
    if not len(hashes):
        return 0
    votes = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 1 << 14):
        part = np.ascontiguousarray(hashes[i: i + (1 << 14)].astype(">u8"))
        votes += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * votes > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, size: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp long) for each row."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in gathered(batches, 4 << 20):
            data, offsets = text_bytes(rows.column("text"))
            data = _lower_ascii(data).tobytes()
            bounds = offsets.tolist()
            fps = np.array([simhash(shingle_hashes(data[a:b], size)) for a, b in zip(bounds, bounds[1:])], np.uint64)
            yield pa.RecordBatch.from_arrays([rows.column("id").combine_chunks(), pa.array(fps.view(np.int64))], ["id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(run, "id long, fp long")


# --- vantage-point trees ------------------------------------------------------

#: Distinct fingerprints that the routing trees are grown on, members of a shard, members of a leaf, visitors held at once.
SAMPLE, SHARD, LEAF, VISITORS = 1 << 16, 1 << 15, 64, 1 << 20
#: Parts of a fingerprint that have a tree of their own, and their bits.
PARTS, PART_BITS = 4, 16


class Forest:
    """Connected sets of positions; keeps the links that joined two of them."""

    def __init__(self, n: int):
        self.up, self.links = np.arange(n), []

    def roots(self) -> np.ndarray:
        while True:
            above = self.up[self.up]
            if (above == self.up).all():
                return above
            self.up = above

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            top = self.roots()
            x, y = top[a], top[b]
            apart = x != y
            a, b, x, y = a[apart], b[apart], x[apart], y[apart]
            high, first = np.unique(np.maximum(x, y), return_index=True)  # each higher root takes one link to a lower one
            self.up[high] = np.minimum(x, y)[first]
            self.links += zip(a[first].tolist(), b[first].tolist())


@dataclass
class Node:
    """A ball and what lies outside it, by the distance of one measure; or a leaf with its shard."""

    measure: int = 0
    vantage: np.uint64 = np.uint64(0)
    middle: int = 0
    inner: Node | None = None
    outer: Node | None = None
    shard: int = -1


def measures(fps: np.ndarray, part: int) -> tuple[np.ndarray, np.ndarray]:
    """The part that a tree searches, and the whole fingerprint for sets that agree in it."""
    return (fps >> np.uint64(PART_BITS * part)) & np.uint64((1 << PART_BITS) - 1), fps


def distance(values: np.ndarray, vantage: np.uint64) -> np.ndarray:
    return np.bitwise_count(values ^ vantage).astype(np.int16)


def split(values: tuple[np.ndarray, np.ndarray], own: np.ndarray) -> tuple[int, np.uint64, int]:
    """(measure, vantage, middle) of the evenest of a few ball cuts of ``own``; both sides hold members if they aren't all equal."""
    best, evenest = (1, values[1][own[0]], 0), -1
    for k in (0, 1):
        for at in {0, len(own) // 3, 2 * len(own) // 3, len(own) - 1}:
            vantage = values[k][own[at]]
            d = distance(values[k][own], vantage)
            for middle in {int(np.median(d)), int(np.median(d)) - 1}:
                side = int((d <= middle).sum())
                if min(side, len(own) - side) > evenest:
                    best, evenest = (k, vantage, middle), min(side, len(own) - side)
        if 4 * evenest >= len(own):
            break
    return best


def grown(fps: np.ndarray, part: int, members: float) -> tuple[Node, int]:
    """A routing tree over a sample, cut until a leaf has at most ``members`` of it; and the number of leaves."""
    values, shards = measures(fps, part), 0
    root = Node()
    work = [(root, np.arange(len(fps)))]
    while work:
        node, own = work.pop()
        if len(own) <= max(members, 1):
            node.shard, shards = shards, shards + 1
            continue
        node.measure, node.vantage, node.middle = split(values, own)
        inside = distance(values[node.measure][own], node.vantage) <= node.middle
        node.inner, node.outer = Node(), Node()
        work += [(node.inner, own[inside]), (node.outer, own[~inside])]
    return root, shards


def reach(measure: int, radius: int, part: int) -> int:
    """How far apart in a measure two fingerprints can be that this part must find; -1: none are left to it.

    Beyond its reach in every part a pair would differ in radius + 1 bits.
    """
    return radius if measure else (radius + PARTS - part) // PARTS - 1


def searched(radius: int) -> list[int]:
    return [part for part in range(PARTS) if reach(0, radius, part) >= 0]


def route(fps: np.ndarray, part: int, root: Node, radius: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(shard, positions, whether it is their home) of all shards.

    What reaches beyond its own value goes down with each value one bit away,
    which leaves a bit less to the overlap of the boundaries; so it comes only
    where such a value could be at home, not wherever single boundaries allow.
    """
    values, wide = measures(fps, part), reach(0, radius, part)
    steps = np.concatenate(([0], 1 << np.arange(PART_BITS))).astype(np.uint64)[: PART_BITS + 1 if wide else 1]
    slack = max(wide - 1, 0)
    aims = (values[0][:, None] ^ steps).ravel()
    work = [(root, np.repeat(np.arange(len(fps)), len(steps)), aims, np.tile(steps == 0, len(fps)))]
    while work:
        node, some, aims, home = work.pop()
        if node.shard >= 0:
            first = np.flatnonzero(np.diff(some, prepend=-1))  # aims of one fingerprint lie together
            yield node.shard, some[first], np.logical_or.reduceat(home, first)
            continue
        d, r = (distance(fps[some], node.vantage), radius) if node.measure else (distance(aims, node.vantage), slack)
        for child, near, own in ((node.inner, d <= node.middle + r, d <= node.middle), (node.outer, d > node.middle - r, d > node.middle)):
            if near.any():
                work.append((child, some[near], aims[near], home[near] & own[near]))


def tree_links(fps: np.ndarray, part: int, own: np.ndarray, visitors: np.ndarray, radius: int, forest: Forest, leaf: int = LEAF) -> dict[str, int]:
    """Link each position of ``own`` with those of ``visitors`` within the radius, so far as this part must find them.

    Returns how many leaves were reached and how many pairs were compared there.
    """
    values, did = measures(fps, part), {"leaves": 0, "compared": 0}
    work = [(own, visitors)]
    while work:
        own, visitors = work.pop()
        if not len(visitors):
            continue
        if len(own) <= leaf:
            did["leaves"] += 1
            did["compared"] += len(own) * len(visitors)
            for at in range(0, len(visitors), 1 << 15):
                some = visitors[at: at + (1 << 15)]
                i, j = np.nonzero(np.bitwise_count(fps[own][:, None] ^ fps[some][None, :]) <= radius)
                forest.link(own[i], some[j])
            continue
        k, vantage, middle = split(values, own)
        r = reach(k, radius, part)
        inside, d = distance(values[k][own], vantage) <= middle, distance(values[k][visitors], vantage)
        if inside.all() or not inside.any():  # equal fingerprints alone: cut by position, which loses nothing
            work += [(own[: len(own) // 2], visitors), (own[len(own) // 2:], visitors)]
            continue
        work += [(own[inside], visitors[d <= middle + r]), (own[~inside], visitors[d > middle - r])]
    return did


def _shard_links(radius: int, leaf: int, most: int):
    """mapInArrow over (shard, guest, fp, id) sorted by shard and guest: members come first, then visitors a chunk at a time."""
    def met(part: int, members: np.ndarray, guests: np.ndarray) -> Iterator[pa.RecordBatch]:
        rows = np.concatenate([members, guests], axis=1)
        forest = Forest(rows.shape[1])
        tree_links(rows[0].view(np.uint64), part, np.arange(members.shape[1]), np.arange(rows.shape[1]) if guests.shape[1] == 0 else np.arange(members.shape[1], rows.shape[1]), radius, forest, leaf)
        if forest.links:
            ends = rows[1][np.array(forest.links)]
            yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(ends[:, i])) for i in (0, 1)], ["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        none = np.zeros((2, 0), np.int64)
        shard, members, guests, closed = None, none, none, False

        def flush(last: bool) -> Iterator[pa.RecordBatch]:
            nonlocal members, guests, closed
            if members.shape[1] and (closed or last):
                if not closed:
                    yield from met(shard % PARTS, members, none)
                if guests.shape[1]:
                    yield from met(shard % PARTS, members, guests)

        for batch in batches:
            rows = np.stack([np.asarray(batch.column(i)).astype(np.int64) for i in range(4)])
            cuts = [0, *(np.flatnonzero((np.diff(rows[0]) != 0) | (np.diff(rows[1]) != 0)) + 1).tolist(), rows.shape[1]]
            for a, b in zip(cuts, cuts[1:]):
                if rows[0, a] != shard:
                    yield from flush(True)
                    shard, members, guests, closed = int(rows[0, a]), none, none, False
                if rows[1, a] == 0:
                    members = np.concatenate([members, rows[2:, a:b]], axis=1)
                    continue
                if not closed:
                    yield from met(shard % PARTS, members, none)
                    closed = True
                guests = np.concatenate([guests, rows[2:, a:b]], axis=1)
                if guests.shape[1] >= most:
                    yield from flush(False)
                    guests = none
        yield from flush(True)

    return run


def near_pairs(distinct: DataFrame, radius: int = 4, shard: int = SHARD, leaf: int = LEAF, sample: int = SAMPLE, most: int = VISITORS) -> DataFrame:
    """Links (a, b) of ids among distinct (fp, id), whose closure is that of all pairs within the radius.

    The sample is a share of the fingerprints by their hash; it only decides
    where shards are cut.
    """
    n = distinct.count()
    share = min(1.0, sample / max(n, 1))
    rows = distinct.select("fp").where(F.pmod(F.xxhash64("fp"), F.lit(1 << 20)) < int(share * (1 << 20)) + 1).collect()
    taken = np.sort(np.array([r["fp"] for r in rows], np.int64)).view(np.uint64)
    trees = [(part, grown(taken, part, max(shard * len(taken) / max(n, 1), 8 if share < 1 else 1))[0]) for part in searched(radius)]

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps, ids = np.asarray(batch.column("fp"), np.int64).view(np.uint64), batch.column("id")
            for part, root in trees:
                for number, some, home in route(fps, part, root, radius):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), PARTS * number + part)), pa.array((~home).astype(np.int64)), pa.array(fps[some].view(np.int64)), ids.take(pa.array(some))], ["shard", "guest", "fp", "id"])

    placed = distinct.select("fp", "id").mapInArrow(place, "shard long, guest long, fp long, id long")
    return placed.repartition(shuffle_partitions(distinct.sparkSession), "shard").sortWithinPartitions("shard", "guest").mapInArrow(_shard_links(radius, leaf, most), "a long, b long")


# --- connected components ----------------------------------------------------

def _with_least(edges: DataFrame, total: int) -> DataFrame:
    """(u, v, m): each edge with the least v of its u; a hub's edges stay where they are."""
    return joined_hot(edges, edges.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n")), "u", total)


#: Links that a piece holds: few links lie in few pieces, so that a round of them leaves few files.
PIECE = 1 << 14


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, root): the smallest node reachable, for the nodes of ``links`` (a, b).

    Alternates the two star contractions (each node's larger neighbours move to
    its smallest one, then its smaller ones do), so rounds grow with the
    logarithm of the size.  Only a change count reaches the driver.
    """
    edges = reliable(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    total = edges.count()
    for _ in range(most_rounds):
        gathered_in = lambda rows, k=1 + 2 * total // PIECE: rows.coalesce(k)
        edges = gathered_in(edges)
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = gathered_in(_with_least(both, 2 * total)).where("v > u").select(F.col("v").alias("u"), F.least("m", "u").alias("v")).where("u <> v").distinct()
        large = reliable(gathered_in(large))
        small = gathered_in(_with_least(large, 2 * total)).select(F.explode(F.array(F.struct(F.col("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").where("u <> v").distinct()
        edges = reliable(gathered_in(small))
        total = edges.count()
        # settled: every node has one parent and no parent has a parent
        state = edges.groupBy("u").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("n")).first()
        parents, children = edges.select("v").distinct(), edges.select("u").distinct()
        if (state["n"] or 0) <= 1 and parents.join(children, F.col("v") == F.col("u"), "left_semi").isEmpty():
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
    raise RuntimeError("components did not settle")


def near_duplicates(docs: DataFrame, size: int = 5, radius: int = 4, id_col: str = "doc_id", text_col: str = "text", shard: int = SHARD) -> DataFrame:
    """(id, fp, component) for each row; component is the smallest id reachable over links."""
    marked = reliable(fingerprints(docs, size, id_col, text_col))
    first = marked.where("id is not null").groupBy("fp").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("n"))
    roots = components(near_pairs(first.select("fp", F.col("first").alias("id")), radius, shard))
    named = first.join(roots, F.col("first") == F.col("node"), "left").select("fp", F.coalesce("root", "first").alias("component"), "n")
    return joined_hot(marked, named, "fp", marked.count()).select("id", "fp", F.when(F.col("id").isNotNull(), F.col("component")).alias("component"))


def deduplicated(docs: DataFrame, size: int = 5, radius: int = 4) -> DataFrame:
    """The rows of ``docs`` (documents columns kept) with one row for each group: that of the smallest id.

    Of repeated rows with that id one stays; rows with a null id stay as they are.
    """
    return one_of_each(docs, near_duplicates(docs, size, radius))


def one_of_each(docs: DataFrame, groups: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose id is the component of ``groups`` (id, component), one for each; and those with a null id."""
    chosen = groups.where("id = component").select(F.col("component").alias("__keep")).distinct()
    kept = docs.join(chosen, docs["doc_id"] == F.col("__keep"), "inner")
    order = Window.partitionBy("__keep").orderBy(*[F.col(c) for c, t in docs.dtypes if not t.startswith("map")])
    kept = kept.withColumn("__n", F.row_number().over(order)).where("__n = 1").drop("__n", "__keep")
    return kept.unionByName(docs.where(docs["doc_id"].isNull()))
