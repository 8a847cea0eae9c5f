"""Session helpers and byte-level text kernels shared by the operators."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The separators of the word pattern [^\x20\x09-\x0D]+.
SEPARATORS = b"\x09\x0a\x0b\x0c\x0d\x20"
#: The same pattern for Java and RE2.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
SPACE_PATTERN = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Evaluate ``value`` once and bind it inside ``body``.

    A lambda variable is the only name that Catalyst can't inline, so an
    expensive array used many times is computed a single time.
    """
    return F.transform(F.array(value), body)[0]


def shared_folder(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: spark.checkpoint.dir, or the context's own.

    Where neither is set, a session on one machine (as in tests) gets a folder
    of its own; on a cluster that is an error.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="cutloom-"))
        folder = spark.sparkContext.getCheckpointDir()
    return folder


def reliable(df: DataFrame) -> DataFrame:
    """Cut the lineage with a checkpoint in the shared folder of the cluster."""
    context = df.sparkSession.sparkContext
    if not context.getCheckpointDir():
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """The rows written once as compressed Parquet in the shared folder and read again: a cheaper cut for wide or many rows."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/cutloom-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: A key is hot when it holds more than this many rows and more than one in this many: at most HOT keys are.
HOT = 1000


def joined_hot(rows: DataFrame, table: DataFrame, key: str, total: int, weight: str = "n") -> DataFrame:
    """``rows`` left-joined with ``table``, whose keys are distinct and whose ``weight`` is each key's number of rows.

    ``total`` is the number of rows.  The table's rows of hot keys, at most HOT,
    are broadcast, so that no task receives all rows of one key; the others meet
    in a shuffled join.
    """
    hot = table.where(F.col(weight) > max(HOT, total // HOT)).drop(weight)
    few, rest = hot.collect(), table.drop(weight)
    if not few:
        return rows.join(rest, key, "left")
    known = rows.sparkSession.createDataFrame(few, hot.schema).withColumn("__hot", F.lit(True))
    tagged = rows.join(F.broadcast(known), key, "left")
    return tagged.where("__hot").drop("__hot").unionByName(tagged.where("__hot is null").select(*rows.columns).join(rest, key, "left"))


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


# --- bytes of an Arrow column -------------------------------------------------

def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string column and its int64 offsets, from zero; null counts as empty."""
    column = pc.fill_null(column, "").cast(pa.large_string())
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64)[column.offset: column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    if data is None or not len(off):
        return np.zeros(0, np.uint8), off - off[0]
    return np.frombuffer(data, np.uint8)[off[0]: off[-1]], off - off[0]


_IS_WORD = np.ones(256, bool)
_IS_WORD[list(SEPARATORS)] = False

_MULTIPLIER = np.uint64(0x9E3779B97F4A7C13)  # odd, 3 modulo 8: small 2-adic valuations of r^k - 1
_INVERSE = np.uint64(pow(int(_MULTIPLIER), -1, 1 << 64))
_BYTE_VALUES = np.random.default_rng(20240611).integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_powers: dict[str, np.ndarray] = {}


def _power_table(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers.get("up", ())) < n:
        size = 1 << max(20, int(n - 1).bit_length())
        for name, base in (("up", _MULTIPLIER), ("down", _INVERSE)):
            steps = np.full(size, base, np.uint64)
            steps[0] = 1
            _powers[name] = np.cumprod(steps, dtype=np.uint64)
    return _powers["up"], _powers["down"]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser, bijective."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def pieces(data: np.ndarray, piece: int) -> Iterator[tuple[int, int]]:
    """Ranges of about ``piece`` bytes that end after a separator, so no word is cut."""
    lo, n = 0, len(data)
    while lo < n:
        hi = min(n, lo + piece)
        if hi < n:
            found = np.flatnonzero(~_IS_WORD[data[lo:hi]])
            if len(found):
                hi = lo + int(found[-1]) + 1
            else:
                while hi < n and _IS_WORD[data[hi - 1]]:
                    ahead = np.flatnonzero(~_IS_WORD[data[hi: hi + piece]])
                    hi = hi + int(ahead[0]) + 1 if len(ahead) else min(n, hi + piece)
        yield lo, hi
        lo = hi


def word_spans(data: np.ndarray, offsets: np.ndarray, lo: int = 0, hi: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words in data[lo:hi]; a document's end also ends a word."""
    hi = len(data) if hi is None else hi
    is_word = _IS_WORD[data[lo:hi]]
    before = np.empty_like(is_word)
    before[:1], before[1:] = False, is_word[:-1]
    after = np.empty_like(is_word)
    after[-1:], after[:-1] = False, is_word[1:]
    edge = offsets[np.searchsorted(offsets, lo, "left"): np.searchsorted(offsets, hi, "left")] - lo
    before[edge[edge < len(is_word)]] = False
    after[edge[edge > 0] - 1] = False
    return np.flatnonzero(is_word & ~before) + lo, np.flatnonzero(is_word & ~after) + lo + 1


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte spans that lie close together: prefix sums of a polynomial, all vectorised."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    lo, hi = int(starts.min()), int(ends.max())
    up, down = _power_table(hi - lo + 1)
    sums = np.zeros(hi - lo + 1, np.uint64)
    np.cumsum(_BYTE_VALUES[data[lo:hi]] * up[: hi - lo], out=sums[1:])
    s, e = starts - lo, ends - lo
    return mix((sums[e] - sums[s]) * down[s] + (e - s).astype(np.uint64))


def hashed_words(data: np.ndarray, offsets: np.ndarray, piece: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
    """For each word, in order: its 64-bit hash and the index of its document."""
    hashes, docs = [], []
    for lo, hi in pieces(data, piece):
        starts, ends = word_spans(data, offsets, lo, hi)
        hashes.append(span_hashes(data, starts, ends))
        docs.append(np.searchsorted(offsets, starts, "right") - 1)
    if not hashes:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return np.concatenate(hashes), np.concatenate(docs)


def chunked(batches: Iterator[pa.RecordBatch], limit: int, text: str = "text") -> Iterator[pa.RecordBatch]:
    """Cut batches where their text passes ``limit`` bytes; a longer document is a chunk of its own."""
    for batch in batches:
        sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(text))), 0), np.int64)
        start, total = 0, 0
        for i, size in enumerate(sizes):
            if i > start and total + size > limit:
                yield batch.slice(start, i - start)
                start, total = i, 0
            total += size
        if start < batch.num_rows:
            yield batch.slice(start)


def gathered(batches: Iterator[pa.RecordBatch], limit: int, text: str = "text") -> Iterator[pa.Table]:
    """Tables of about ``limit`` bytes of text, from however many batches that takes."""
    held, total = [], 0
    for batch in chunked(batches, limit, text):
        size = int(pc.sum(pc.fill_null(pc.binary_length(batch.column(batch.schema.get_field_index(text))), 0)).as_py() or 0)
        if held and total + size > limit:
            yield pa.Table.from_batches(held).combine_chunks()
            held, total = [], 0
        held.append(batch)
        total += size
    if held:
        yield pa.Table.from_batches(held).combine_chunks()
