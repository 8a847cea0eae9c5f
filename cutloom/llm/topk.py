"""Exact top-k inner products by descending length with rotated partial sums.

A first pass scores every query against some of the longest vectors (a bounded
number, the same for all queries), so each starts with a k-th score to beat.  Vectors
are cut into blocks in order of their length (a range partition), and queries
into shards in order of the length that a vector must have to reach their k-th
score (k-th score over the query's own length, by Cauchy-Schwarz); a block goes
only to the shards that it can reach.  A task holds one shard of queries and
some blocks, longest first, and skips a block where the product of lengths can't
reach a query's k-th score.  In a block, both sides are rotated by the right
singular vectors of the corpus; the inner product over the leading directions
plus the product of the remaining lengths bounds the score, and only columns
whose bound reaches some query's k-th score are multiplied out, in integers.
Each task's k best are merged by a window; ties go to the smaller id.

The rotation is fitted to the second moments of all vectors (one matrix of the
dimension squared); it only affects speed.

Defined results: vectors that are null or hold null or non-finite components
take no part; shorter vectors count as padded with zeros; repeated rows are
candidates of their own, and a query leaves out all rows with its own id; rows
of a query that repeat its id and vector are one query, and a query id with
several vectors has k rows for each of them; a query with a null id takes no
part; a component beyond 2^62 in size after scaling counts as 2^62 with its sign,
products are exact, and a score that leaves 64 bits is given as the nearest long;
an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cutloom.llm.common import shuffle_partitions, stored


#: Components are held within this size, so that they are longs.
LARGEST = float(1 << 62)
#: How many of the longest vectors give queries their first k-th score.
LONGEST = 4096


def quantised(vectors: DataFrame, id_col: str, vector_col: str, scale: int) -> DataFrame:
    """(id, v array<long>): floor(scale * x) of each component, in double."""
    v = F.col(vector_col)
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x.cast("double")) & (F.abs(x.cast("double")) < float("inf")))
    return vectors.where(v.isNotNull() & fine & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.transform(v, lambda x: F.floor(F.greatest(F.lit(-LARGEST), F.least(F.lit(LARGEST), F.lit(float(scale)) * x.cast("double")))).cast("long")).alias("v"))


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    sizes = np.asarray(pc.list_value_length(column), np.int64)
    out = np.zeros((len(column), width), np.int64)
    flat = np.asarray(column.flatten(), np.int64)
    row = np.repeat(np.arange(len(column)), sizes)
    out[row, np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)] = flat
    return out


def _moments(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros((width, width)), 0
        for batch in batches:
            m = _matrix(batch.column(0), width).astype(np.float64)
            total += m.T @ m
            n += len(m)
        if n:
            yield pa.RecordBatch.from_pydict({"i": np.arange(width), "n": [n] * width, "row": pa.array(list(total), pa.list_(pa.float64()))})

    return run


def rotation(ints: DataFrame, width: int) -> tuple[np.ndarray, int]:
    """Right singular vectors by falling singular value, and the number of vectors."""
    rows = ints.select("v").mapInArrow(_moments(width), "i long, n long, row array<double>")
    sums = rows.groupBy("i").agg(F.sum("n").alias("n"), F.array(*[F.sum(F.get("row", F.lit(j))) for j in range(width)]).alias("row")).orderBy("i").collect()
    if not sums:
        return np.eye(max(width, 1)), 0
    _, vectors = np.linalg.eigh(np.array([r["row"] for r in sums]))
    return vectors[:, ::-1].copy(), sums[0]["n"]


def _unpack(ids: bytes, m: bytes, width: int) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(ids, np.int64), np.frombuffer(m, np.int64).reshape(-1, width)


def _product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact integer products; by floating point where that is exact, by Python's integers (held within 64 bits) where they could leave 64 bits."""
    if not a.size or not b.size:
        return a @ b.T
    rows, columns = np.abs(a).max(axis=1).astype(np.float64), np.abs(b).max(axis=1).astype(np.float64)
    most = rows.max() * columns.max() * a.shape[1]
    if most < 2**53:
        return np.rint(a.astype(np.float64) @ b.T.astype(np.float64)).astype(np.int64)
    if most < 2**62:
        return a @ b.T
    out, wide = np.zeros((len(a), len(b)), np.int64), np.outer(rows, columns) * a.shape[1] >= 2**62
    big, fine = wide.any(axis=0), ~wide.any(axis=0)
    out[:, fine] = a @ b[fine].T
    low, high = -(1 << 63) + 1, (1 << 63) - 1
    exact = a.astype(object) @ b[big].astype(object).T
    out[:, big] = np.array([[min(high, max(low, int(x))) for x in row] for row in exact], np.int64).reshape(len(a), int(big.sum()))
    return out


def best_of(query_ids: np.ndarray, queries: np.ndarray, blocks: list[tuple[np.ndarray, np.ndarray]], k: int, turn: np.ndarray, head: int, least: np.ndarray | None = None) -> Iterator[tuple[int, int, int, int]]:
    """(query, row of the query, vec, score) of each query's k best over the blocks; ``least`` are k-th scores that are known already."""
    low = np.iinfo(np.int64).min
    scores = np.full((len(queries), k), low)
    found = np.full((len(queries), k), np.iinfo(np.int64).max)
    rotated = queries @ turn
    q_len, q_tail = np.linalg.norm(rotated, axis=1), np.linalg.norm(rotated[:, head:], axis=1)
    blocks = sorted(blocks, key=lambda b: -float((b[1].astype(np.float64) ** 2).sum(axis=1).max()))
    for ids, m in blocks:
        x = m @ turn
        length = np.linalg.norm(x, axis=1)
        floor = np.where(scores[:, -1] == low, -np.inf, scores[:, -1].astype(np.float64))
        if least is not None:
            floor = np.maximum(floor, least)
        slack = 0.5 + 1e-9 * q_len * length.max()
        able = np.flatnonzero(q_len * length.max() >= floor - slack)
        if not len(able):
            continue
        bound = rotated[able, :head] @ x[:, :head].T + q_tail[able, None] * np.linalg.norm(x[:, head:], axis=1)[None, :]
        columns = np.flatnonzero((bound >= (floor - slack)[able, None]).any(axis=0))
        if not len(columns):
            continue
        exact = _product(queries[able], m[columns])
        exact[query_ids[able][:, None] == ids[columns][None, :]] = low
        if exact.shape[1] > 8 * k:  # keep ties of the k-th
            kth = np.partition(exact, exact.shape[1] - k, axis=1)[:, exact.shape[1] - k]
        else:
            kth = np.full(len(able), low)
        kth = np.maximum(kth, scores[able, -1])
        r, c = np.nonzero((exact >= kth[:, None]) & (exact > low))
        owner = np.concatenate((able[r], np.repeat(able, k)))
        s = np.concatenate((exact[r, c], scores[able].ravel()))
        v = np.concatenate((ids[columns][c], found[able].ravel()))
        order = np.lexsort((v, ~s, owner))  # ~s falls as s rises, without overflow
        owner, s, v = owner[order], s[order], v[order]
        rank = np.arange(len(owner)) - np.searchsorted(owner, owner, "left")
        top = rank < k
        scores[owner[top], rank[top]], found[owner[top], rank[top]] = s[top], v[top]
    for i in range(len(queries)):
        for j in range(k):
            if scores[i, j] > low:
                yield int(query_ids[i]), i, int(found[i, j]), int(scores[i, j])


def _longest(ints: DataFrame, most: int) -> DataFrame:
    """(id, v) of about ``most`` of the longest among (id, v, l: squared length): whole steps of an eighth of a power of two, and of the last step a share by hash."""
    step = F.floor(8 * F.log2(F.col("l") + 1)).cast("int")
    share, last = 1.0, -1
    for r in sorted(ints.groupBy(step.alias("step")).agg(F.count(F.lit(1)).alias("n")).collect(), key=lambda r: -r["step"]):
        if r["n"] > most:
            share, last = most / r["n"], r["step"]
            break
        most -= r["n"]
    drawn = F.pmod(F.xxhash64("id", "v"), F.lit(1 << 30)) < int(share * (1 << 30))
    return ints.where((step > last) | ((step == last) & drawn)).select("id", "v")


def _first_scores(queries: DataFrame, longest: tuple[np.ndarray, np.ndarray], k: int, width: int, block: int) -> DataFrame:
    """``queries`` (id, v) with q, their length, and least, their k-th best score among the longest vectors (minus infinity if there are fewer)."""
    shared = queries.sparkSession.sparkContext.broadcast(longest)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, m = shared.value
        for batch in batches:
            for start in range(0, batch.num_rows, block):
                part = batch.slice(start, block)
                q, own = _matrix(part.column("v"), width), np.asarray(part.column("id"), np.int64)
                least = np.full(len(q), -np.inf)
                if len(ids) > k:
                    scores = _product(q, m)
                    others = own[:, None] != ids[None, :]
                    scores[~others] = np.iinfo(np.int64).min
                    kth = np.partition(scores, len(ids) - k, axis=1)[:, len(ids) - k].astype(np.float64)
                    least = np.where(others.sum(axis=1) >= k, kth, -np.inf)
                length = np.linalg.norm(q.astype(np.float64), axis=1)
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("v"), pa.array(length), pa.array(least)], ["id", "v", "q", "least"])

    return queries.mapInArrow(run, "id long, v array<long>, q double, least double")


def _chunks(size: int, width: int, blocks: int):
    """Blocks of rows as bytes, in the order of the stream, with the greatest length in each; ``blocks`` of them are a chunk."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, k = TaskContext.get().partitionId(), 0
        for batch in batches:
            for start in range(0, batch.num_rows, size):
                some = batch.slice(start, size)
                m = _matrix(some.column("v"), width)
                longest = float(np.sqrt((m.astype(np.float64) ** 2).sum(axis=1).max()))
                yield pa.RecordBatch.from_arrays([pa.array([(part << 32) + k // blocks], pa.int64()), pa.array([longest]), pa.array([np.asarray(some.column("id"), np.int64).tobytes()], pa.binary()), pa.array([m.tobytes()], pa.binary())], ["c", "longest", "ids", "m"])
                k += 1

    return run


def _query_blocks(size: int, width: int):
    """Queries (s, id, v, least), sorted by s, as blocks of one shard each."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            shards = np.asarray(batch.column("s"), np.int64)
            cuts = sorted({0, len(shards), *range(0, len(shards), size), *(np.flatnonzero(np.diff(shards)) + 1).tolist()})
            for a, b in zip(cuts, cuts[1:]):
                some = batch.slice(a, b - a)
                columns = [pa.array([x], t) for x, t in ((int(shards[a]), pa.int64()), (np.asarray(some.column("id"), np.int64).tobytes(), pa.binary()), (_matrix(some.column("v"), width).tobytes(), pa.binary()), (np.asarray(some.column("least"), np.float64).tobytes(), pa.binary()))]
                yield pa.RecordBatch.from_arrays(columns, ["s", "ids", "m", "least"])

    return run


def top_k(vectors: DataFrame, is_query: Column, k: int = 5, scale: int = 256, head: int = 16, block: int = 1024, shard: int = 4096, id_col: str = "vec_id", vector_col: str = "embedding", longest: int = LONGEST) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k best among all other rows.

    ``block`` vectors and ``shard`` queries bound what a task holds at once;
    one number for each shard of queries reaches the driver.
    """
    spark = vectors.sparkSession
    ints = quantised(vectors, id_col, vector_col, scale)
    width = max(1, ints.agg(F.max(F.size("v"))).first()[0] or 0)
    turn, n = rotation(ints, width)
    head = min(head, width)
    length = F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    parts = max(1, min(shuffle_partitions(spark), -(-n // block)))
    top = _longest(ints.withColumn("l", length), longest).toArrow()
    first = np.asarray(top.column("id"), np.int64), _matrix(top.column("v"), width)
    # queries in shards by the length that a vector must have to matter to them
    asked = quantised(vectors.where(is_query), id_col, vector_col, scale)
    asked = asked.select("id", F.concat("v", F.array_repeat(F.lit(0).cast("long"), F.lit(width) - F.size("v"))).alias("v")).distinct()
    # a query whose own length is zero scores zero with all; a little less is asked for than what rounding could hide
    needed = F.when((F.col("least") <= 0) | (F.col("q") <= 0), 0.0).otherwise((F.col("least") - 1) / F.col("q") * (1 - 1e-9))
    asked = stored(_first_scores(asked, first, k, width, block).withColumn("needed", needed))
    shards = max(1, -(-asked.count() // shard))
    ranged = asked.repartitionByRange(shards, "needed", "id").select(F.spark_partition_id().cast("long").alias("s"), "id", "v", "least", "needed")
    ranged = stored(ranged)
    reach = {r["s"]: r["needed"] for r in ranged.groupBy("s").agg(F.min("needed").alias("needed")).collect()}
    queries = ranged.repartition(shards, "s").sortWithinPartitions("s").mapInArrow(_query_blocks(block, width), "s long, ids binary, m binary, least binary")
    held = ints.withColumn("l", -length).repartitionByRange(parts, "l", "id").sortWithinPartitions("l", "id").select("id", "v").mapInArrow(_chunks(block, width, 8), "c long, longest double, ids binary, m binary")
    held = stored(held)
    limits = sorted(reach.items())
    wanted = F.filter(F.array(*[F.struct(F.lit(s).alias("s"), F.lit(float(x)).alias("x")) for s, x in limits] or [F.struct(F.lit(-1).alias("s"), F.lit(0.0).alias("x"))]), lambda t: t["x"] <= F.col("longest"))
    held = held.select(F.explode(wanted).alias("t"), "c", "ids", "m").select(F.col("t.s").cast("long").alias("s"), "c", "ids", "m")
    sent = held.select("s", F.col("c").alias("chunk")).distinct().join(queries, "s").withColumnRenamed("s", "shard")

    def search(left: pa.Table, right: pa.Table) -> pa.Table:
        blocks = [_unpack(a, b, width) for a, b in zip(right.column("ids").to_pylist(), right.column("m").to_pylist())]
        rows = []
        for a, b, c in zip(left.column("ids").to_pylist(), left.column("m").to_pylist(), left.column("least").to_pylist()):
            ids, m = _unpack(a, b, width)
            tags = [xxhash.xxh64_intdigest(v.tobytes()) - (1 << 63) for v in m]
            rows += [(q, tags[i], v, s) for q, i, v, s in best_of(ids, m, blocks, k, turn, head, np.frombuffer(c, np.float64))]
        columns = list(zip(*rows)) or [(), (), (), ()]
        return pa.table({name: pa.array(c, pa.int64()) for name, c in zip(("query_id", "tag", "vec_id", "score"), columns)})

    found = sent.groupBy("shard", "chunk").cogroup(held.groupBy("s", "c")).applyInArrow(search, "query_id long, tag long, vec_id long, score long")
    rank = F.row_number().over(Window.partitionBy("query_id", "tag").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
