"""Language-model scores of documents: stupid backoff over counts of the whole corpus.

A token w after context c scores count(c w) / count(c) where that n-gram
occurs, else ``backoff`` times the score after the context without its first
word, and at last max(count(w), 1) / tokens.  All counts leave out the scored
document itself, else no n-gram of it could be unseen.  A document's score is
the sum over its tokens of round(10^6 * log10(score)), a long, so that sums are
exact in any order.

The relations, column-packed.  Documents are dealt to blocks by a hash, so a
block is a set of documents that any recomputation finds again, whatever the
order of its rows; compressed, they move once, in a shuffle that both readers
share.  A block's n-grams are exploded, made distinct and cut by hash range: one
row for each (range, block) with sorted 64-bit hashes and counts.  Grouped by
range they are the count table of that range; its totals are joined back to the
blocks (a co-group by block) and summed per document.  An n-gram moves in about
six bytes instead of a row of its own; a hot n-gram is one entry per block.

Blocks and ranges grow with the root of the corpus where a message would
otherwise hold fewer than ``MESSAGE`` n-grams (from some 250 GB on), so messages
grow in proportion to the n-grams at every size.

Defined results: null and empty texts have no tokens and score 0; repeated rows
are documents of their own; a very long text is a block's only large one and is
scored whole; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutloom.llm.common import gathered, hashed_words, mix, shuffle_partitions, text_bytes

BACKOFF, ORDER = 0.4, 3
_SCORED_BYTES, _PACKED_BYTES = 2 << 20, 16 << 20
#: The fewest n-grams that a message is to hold on average.
MESSAGE = 512
_ORDER_KEYS = [np.uint64(0xA0761D6478BD642F), np.uint64(0xE7037ED1A0B428DB), np.uint64(0x8EBC6AF09C88C6E3), np.uint64(0x589965CC75374CC3), np.uint64(0x1D8E4E27C47D124F)]


# --- packing ------------------------------------------------------------------

def pack(values: np.ndarray) -> bytes:
    """Non-negative integers as compressed byte planes."""
    planes = np.ascontiguousarray(values.astype("<u8").view(np.uint8).reshape(-1, 8).T)
    return zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def unpack(blob: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(blob), np.uint8).reshape(8, -1)
    return np.ascontiguousarray(planes.T).view("<u8").ravel().astype(np.uint64)


def pack_sorted(values: np.ndarray) -> bytes:
    steps = values.copy()
    steps[1:] -= values[:-1]
    return pack(steps)


def unpack_sorted(blob: bytes) -> np.ndarray:
    return np.cumsum(unpack(blob), dtype=np.uint64)


def freeze(ids: pa.Array, texts: pa.Array) -> bytes:
    """Documents as compressed columns."""
    data, offsets = text_bytes(texts)
    valid = np.asarray(ids.is_valid()).astype(np.uint8)
    raw = b"".join([np.int64(len(ids)).tobytes(), np.asarray(ids.fill_null(0), np.int64).tobytes(), valid.tobytes(), np.diff(offsets).astype(np.int64).tobytes(), data.tobytes()])
    return zstandard.ZstdCompressor(level=6).compress(raw)


def thaw(blobs: list[bytes]) -> pa.Table:
    """(id, text) of the documents of some blobs."""
    tables = []
    for blob in blobs:
        raw = zstandard.ZstdDecompressor().decompress(blob)
        n = int(np.frombuffer(raw, np.int64, 1)[0])
        ids, valid, sizes = np.frombuffer(raw, np.int64, n, 8), np.frombuffer(raw, np.uint8, n, 8 + 8 * n), np.frombuffer(raw[8 + 9 * n: 8 + 17 * n], np.int64)
        offsets = np.concatenate(([0], np.cumsum(sizes))).astype(np.int64)
        texts = pa.LargeStringArray.from_buffers(n, pa.py_buffer(offsets.tobytes()), pa.py_buffer(raw[8 + 17 * n:]))
        tables.append(pa.table({"id": pa.array(ids, pa.int64(), mask=valid == 0), "text": texts}))
    return pa.concat_tables(tables).combine_chunks()


# --- n-grams of a block -------------------------------------------------------

def exploded(table: pa.Table, order: int) -> tuple[list[np.ndarray], list[np.ndarray], np.ndarray]:
    """For each n: the hash of the n-gram ending at each token and whether it lies inside its document; the tokens' documents."""
    data, offsets = text_bytes(table.column("text"))
    words, docs = hashed_words(data, offsets)
    grams, inside = [mix(words ^ _ORDER_KEYS[0])], [np.ones(len(words), bool)]
    chain = words
    for n in range(1, order):
        longer = np.zeros_like(chain)
        longer[1:] = mix(chain[:-1] + _ORDER_KEYS[n]) + words[1:] * np.uint64(0x2545F4914F6CDD1D)
        fits = np.zeros(len(words), bool)
        fits[n:] = docs[n:] == docs[:-n]
        chain = longer
        grams.append(mix(chain ^ _ORDER_KEYS[n]))
        inside.append(fits)
    return grams, inside, docs


def _distinct(grams: list[np.ndarray], inside: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """The sorted hashes and their counts; each order is made distinct alone, which holds less at once."""
    each = [np.unique(g[i], return_counts=True) for g, i in zip(grams, inside)]
    keys, counts = (np.concatenate(x) for x in zip(*each))
    place = np.argsort(keys)
    return keys[place], counts[place]


def range_of(hashes: np.ndarray, ranges: int) -> np.ndarray:
    """Equal ranges of the hash space, in order."""
    return ((hashes >> np.uint64(32)) * np.uint64(ranges)) >> np.uint64(32)


def _packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(block, docs) from (id, text, block): what a task holds of a block, in one value for every few megabytes read."""
    for rows in gathered(batches, _PACKED_BYTES):
        block = np.asarray(rows.column("block"), np.int64)
        order = np.argsort(block, kind="stable")
        cuts = [0, *(np.flatnonzero(np.diff(block[order])) + 1).tolist(), len(block)]
        for a, b in zip(cuts, cuts[1:]):
            some = rows.take(pa.array(order[a:b]))
            blob = freeze(some.column("id").combine_chunks(), some.column("text"))
            yield pa.RecordBatch.from_arrays([pa.array([int(block[order[a]])], pa.int64()), pa.array([blob], pa.binary())], ["block", "docs"])


def _requests(order: int, ranges: int):
    """A block's distinct n-grams with their counts, cut by hash range."""
    def run(key: tuple, table: pa.Table) -> pa.Table:
        keys, counts = _distinct(*exploded(thaw(table.column("docs").to_pylist()), order)[:2])
        cuts = np.searchsorted(range_of(keys, ranges), np.arange(ranges + 1, dtype=np.uint64))
        held = np.flatnonzero(np.diff(cuts)).tolist()
        grams = [pack_sorted(keys[cuts[r]: cuts[r + 1]]) for r in held]
        each = [pack(counts[cuts[r]: cuts[r + 1]].astype(np.uint64)) for r in held]
        return pa.table({"place": pa.array(held, pa.int64()), "block": pa.array([key[0].as_py()] * len(held), pa.int64()), "grams": pa.array(grams, pa.binary()), "counts": pa.array(each, pa.binary())})

    return run


def _count_range(key: tuple, table: pa.Table) -> pa.Table:
    """The count table of one hash range, answered to each block."""
    keys = [unpack_sorted(x) for x in table.column("grams").to_pylist()]
    counts = np.concatenate([unpack(x) for x in table.column("counts").to_pylist()])
    _, back = np.unique(np.concatenate(keys), return_inverse=True)
    totals = np.bincount(back, weights=counts.astype(np.float64)).astype(np.uint64)[back]
    cuts = np.cumsum([0, *map(len, keys)])
    return pa.table({"block": table.column("block"), "place": table.column("place"), "totals": pa.array([pack(totals[a:b]) for a, b in zip(cuts, cuts[1:])], pa.binary())})


def score_tokens(grams: list[np.ndarray], inside: list[np.ndarray], docs: np.ndarray, keys: np.ndarray, totals: np.ndarray, tokens: int, n_docs: int, backoff: float) -> dict[str, np.ndarray]:
    """Sums for each document; ``totals`` are the corpus counts of the sorted ``keys``."""
    own_tokens = np.bincount(docs, minlength=n_docs)
    rest = []
    for gram, fits in zip(grams, inside):
        # the corpus count minus the document's own occurrences of the same n-gram
        left = np.zeros(len(gram), np.int64)
        if fits.any():
            real = gram[fits]
            _, back, own = np.unique(mix(real + mix(docs[fits].astype(np.uint64))), return_inverse=True, return_counts=True)
            asked, at = np.unique(real, return_inverse=True)  # sorted, so the lookups run along the keys
            left[fits] = totals[np.searchsorted(keys, asked)][at].astype(np.int64) - own[back]
        rest.append(left)
    score = np.maximum(rest[0], 1) / np.maximum(tokens - own_tokens[docs], 1)
    hits = {"n_unseen": rest[0] <= 0}
    level = np.zeros(len(docs), np.int64)
    context_ok = [None, *inside[1:]]
    for n in range(1, len(grams)):
        before = np.zeros_like(rest[n - 1])
        before[1:] = rest[n - 1][:-1]
        seen = context_ok[n] & (rest[n] > 0)
        score = np.where(context_ok[n], np.where(seen, rest[n] / np.maximum(before, 1), backoff * score), score)
        level = np.where(seen, n, level)
    micro = np.rint(1e6 * np.log10(score)).astype(np.int64)
    out = {"n_tokens": own_tokens, "n_unseen": np.bincount(docs[hits["n_unseen"]], minlength=n_docs)}
    out["n_full"] = np.bincount(docs[level == len(grams) - 1], minlength=n_docs) if len(grams) > 1 else own_tokens
    total = np.zeros(n_docs, np.int64)
    np.add.at(total, docs, micro)
    return out | {"score_micro": total}


def _score_block(order: int, backoff: float, tokens: int):
    def score(held: pa.Table, answers: pa.Table) -> pa.Table:
        docs_table = thaw(held.column("docs").to_pylist())
        keys = _distinct(*exploded(docs_table, order)[:2])[0]
        places, blobs = np.asarray(answers.column("place")), answers.column("totals").to_pylist()
        totals = np.concatenate([np.zeros(0, np.uint64), *[unpack(blobs[i]) for i in np.argsort(places)]])
        if len(totals) != len(keys):
            raise RuntimeError("a block's n-grams and the counts answered to it differ")
        out = []
        # documents need only the totals, so they are scored a few at a time
        for some in gathered(iter(docs_table.to_batches()), _SCORED_BYTES):
            grams, inside, docs = exploded(some, order)
            sums = score_tokens(grams, inside, docs, keys, totals, tokens, some.num_rows, backoff)
            out.append(pa.table({"id": some.column("id"), **{k: pa.array(v, pa.int64()) for k, v in sums.items()}}))
        return pa.concat_tables(out)

    return score


def corpus_size(docs: DataFrame) -> tuple[int, int]:
    """Tokens and bytes of the whole corpus."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = size = 0
        for table in gathered(batches, 4 << 20):
            data, offsets = text_bytes(table.column("text"))
            words, size = words + len(hashed_words(data, offsets)[0]), size + len(data)
        yield pa.RecordBatch.from_pydict({"words": [words], "size": [size]})

    row = docs.select("text").mapInArrow(run, "words long, size long").agg(F.sum("words").alias("words"), F.sum("size").alias("size")).first()
    return row["words"] or 0, row["size"] or 0


def sized(size: int, block_bytes: int, range_bytes: int) -> tuple[int, int]:
    """Numbers of blocks and of ranges for a corpus of ``size`` bytes."""
    grow = max(1.0, (MESSAGE * size / (block_bytes * range_bytes)) ** 0.5)
    return max(1, int(-(-size // (block_bytes * grow)))), max(1, int(-(-size // (range_bytes * grow))))


def in_blocks(rows: DataFrame, blocks: int) -> DataFrame:
    """(block, docs), dealt by block.  The partition takes part in the hash, so that equal rows of many partitions are no hot block."""
    dealt = rows.withColumn("block", F.pmod(F.xxhash64("id", "text", F.spark_partition_id()), F.lit(blocks)))
    parts = max(1, min(blocks, 4 * shuffle_partitions(rows.sparkSession)))
    return dealt.mapInArrow(_packed, "block long, docs binary").repartition(parts, "block")


def backoff_scores(docs: DataFrame, order: int = ORDER, backoff: float = BACKOFF, block_bytes: int = 12 << 20, range_bytes: int = 8 << 20, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_tokens, n_unseen, n_full, score_micro) for each row.

    n_unseen: tokens that no other document has; n_full: tokens scored at the
    full order.  ``range_bytes`` of text share one hash range of the counts.
    """
    if not 1 <= order <= len(_ORDER_KEYS):
        raise ValueError(f"order must be 1 to {len(_ORDER_KEYS)}")
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    tokens, size = corpus_size(rows)
    blocks, ranges = sized(size, block_bytes, range_bytes)
    held = in_blocks(rows, blocks)
    asked = held.groupBy("block").applyInArrow(_requests(order, ranges), "place long, block long, grams binary, counts binary")
    answered = asked.groupBy("place").applyInArrow(_count_range, "block long, place long, totals binary")
    return held.groupBy("block").cogroup(answered.groupBy("block")).applyInArrow(_score_block(order, backoff, tokens), "id long, n_tokens long, n_unseen long, n_full long, score_micro long")
