"""Token counts of documents through a table of distinct pre-tokens.

No token crosses the border of a pre-token, so a document's count is the sum
over its pre-tokens of frequency times pieces, plus one for each special string
inside it.  Three relations say that:

* vocabulary(piece, n, tokens): every distinct pre-token of the corpus with its
  frequency; its pieces are counted once, after the grouping.
* frequencies of each document.  The ``HOT`` most frequent short pre-tokens are
  a table of bounded size, which travels to the tasks and is summed where the
  text is read; only rare ones become (row, piece, n), so that few rows move and
  none of their keys is hot.
* rare frequencies joined to the vocabulary, summed by row with what was known.

Ids of a document's tokens are never made.

Defined results: null and empty texts have no bytes and no tokens; repeated
rows are counted each; a text of any length is one row, and a pre-token of any
length one entry; an empty table gives no rows.
"""

from __future__ import annotations

import json
import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutloom.llm.common import gathered, stored

#: Fixed value: the pre-token pattern of the byte-level tokenizer files.
PRE_TOKENS = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Characters whose classes all Unicode versions since 7.0 agree on; a text with others is cut by the library itself.
SETTLED = "[\x00-\x1b\x20-\u04ff\u2000-\u2064]*"
#: The bound of the table that travels: entries, and bytes of one.
HOT, HOT_BYTES = 1 << 18, 256
_MOST_HELD = 200_000

_settled = re.compile(SETTLED)


def _settled_pattern() -> re.Pattern:
    """The pre-token pattern for settled texts, its classes spelled out as ranges: the standard module cuts twice as fast with them."""
    settled = [chr(c) for c in range(0x2065) if _settled.fullmatch(chr(c))]

    def members(kind: str) -> str:
        codes = [ord(c) for c in settled if regex.fullmatch(kind, c)]
        starts = [c for i, c in enumerate(codes) if i == 0 or codes[i - 1] != c - 1]
        ends = [c for i, c in enumerate(codes) if i == len(codes) - 1 or codes[i + 1] != c + 1]
        return "".join(f"\\u{a:04x}-\\u{b:04x}" for a, b in zip(starts, ends))

    letters, numbers, spaces = members(r"\p{L}"), members(r"\p{N}"), members(r"\s")
    spelled = PRE_TOKENS.replace(r"[^\s\p{L}\p{N}]", f"[^{spaces}{letters}{numbers}]").replace(r"\p{L}", f"[{letters}]").replace(r"\p{N}", f"[{numbers}]")
    return re.compile(spelled.replace(r"\S", f"[^{spaces}]").replace(r"\s", f"[{spaces}]"))


_pattern = _settled_pattern()


@lru_cache(maxsize=4)
def _tokenizer(path: str):
    """The library's tokenizer and the pattern of its special strings, or None."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    with open(path, encoding="utf-8") as f:
        text = f.read()
    spec = json.loads(text)
    before = spec.get("pre_tokenizer") or {}
    if spec["model"]["type"] != "BPE" or spec.get("normalizer") or before.get("type") != "ByteLevel" or before.get("add_prefix_space") or not before.get("use_regex", True):
        raise ValueError("a byte-level BPE tokenizer file without a normalizer or prefix space is needed")
    added = spec.get("added_tokens", [])
    if any(t.get("single_word") or t.get("lstrip") or t.get("rstrip") for t in added):
        raise ValueError("special strings that take in what stands beside them aren't known here")
    tokenizer = Tokenizer.from_str(text)
    tokenizer.no_truncation()
    tokenizer.no_padding()
    special = re.compile("|".join(re.escape(t["content"]) for t in sorted(added, key=lambda t: -len(t["content"])))) if added else None
    return tokenizer, special


def pre_tokens(path: str, text: str) -> tuple[list[str], int]:
    """The pre-tokens of a text in order, and how many special strings it holds."""
    tokenizer, special = _tokenizer(path)
    segments = special.split(text) if special is not None and special.search(text) else [text]
    out: list[str] = []
    for s in segments:
        if _settled.fullmatch(s):
            out += _pattern.findall(s)
        else:
            out += [s[a:b] for _, (a, b) in tokenizer.pre_tokenizer.pre_tokenize_str(s)]
    return out, len(segments) - 1


def count_pieces(path: str, pieces: list[str]) -> list[int]:
    """Tokens of each pre-token."""
    tokenizer = _tokenizer(path)[0]
    out: list[int] = []
    for start in range(0, len(pieces), 5000):
        out += [len(e) for e in tokenizer.encode_batch(pieces[start: start + 5000], add_special_tokens=False)]
    return out


def vocabulary(docs: DataFrame, path: str, text_col: str = "text") -> DataFrame:
    """(piece, n, tokens): each distinct pre-token, its frequency in the corpus, its pieces."""
    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: Counter = Counter()

        def flush() -> Iterator[pa.RecordBatch]:
            items = list(held.items())
            for i in range(0, len(items), 20_000):
                yield pa.RecordBatch.from_arrays([pa.array([x[k] for x in items[i: i + 20_000]], t) for k, t in ((0, pa.string()), (1, pa.int64()))], ["piece", "n"])
            held.clear()

        for rows in gathered(batches, 4 << 20):
            for text in rows.column("text").to_pylist():
                held.update(pre_tokens(path, text)[0])
                if len(held) > _MOST_HELD:
                    yield from flush()
        yield from flush()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            tokens = pa.array(count_pieces(path, batch.column("piece").to_pylist()), pa.int64())
            yield pa.RecordBatch.from_arrays([*batch.columns, tokens], ["piece", "n", "tokens"])

    found = docs.select(F.coalesce(F.col(text_col), F.lit("")).alias("text")).mapInArrow(read, "piece string, n long")
    return found.groupBy("piece").agg(F.sum("n").alias("n")).mapInArrow(count, "piece string, n long, tokens long")


def frequent(words: DataFrame, most: int = HOT, most_bytes: int = HOT_BYTES) -> dict[str, int]:
    """Pieces of the most frequent short pre-tokens: all from the least frequency on that leaves at most ``most``.

    Frequencies are found through a histogram in steps of an eighth of a power
    of two, so no more than ``most`` entries ever reach the driver.
    """
    step = F.floor(8 * F.log2("n")).cast("int")
    short = words.where(F.octet_length("piece") <= most_bytes)
    sizes = sorted(((r["step"], r["c"]) for r in short.groupBy(step.alias("step")).agg(F.count(F.lit(1)).alias("c")).collect()), reverse=True)
    least, total = None, 0
    for at, c in sizes:
        total += c
        if total > most:
            break
        least = at
    return {} if least is None else {r["piece"]: r["tokens"] for r in short.where(step >= least).select("piece", "tokens").collect()}


def token_counts(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT, hot_bytes: int = HOT_BYTES) -> DataFrame:
    """(id, n_bytes, n_tokens) for each row."""
    words = stored(vocabulary(docs, path, text_col))
    known = docs.sparkSession.sparkContext.broadcast(frequent(words, hot, hot_bytes))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = known.value
        for rows in gathered(batches, 4 << 20):
            sizes, sums, rare = [], [], []
            for text in rows.column("text").to_pylist():
                found, total = pre_tokens(path, text)
                others = []
                for piece, n in Counter(found).items():
                    tokens = table.get(piece)
                    if tokens is None:
                        others.append({"piece": piece, "n": n})
                    else:
                        total += n * tokens
                sizes.append(len(text.encode()))
                sums.append(total)
                rare.append(others)
            kind = pa.list_(pa.struct([("piece", pa.string()), ("n", pa.int64())]))
            yield pa.RecordBatch.from_arrays([rows.column("id").combine_chunks(), pa.array(sizes, pa.int64()), pa.array(sums, pa.int64()), pa.array(rare, kind)], ["id", "n_bytes", "known", "rare"])

    texts = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    rows = stored(texts.mapInArrow(read, "id long, n_bytes long, known long, rare array<struct<piece:string,n:bigint>>").withColumn("row", F.monotonically_increasing_id()))
    rare = rows.select("row", F.explode("rare").alias("x")).select("row", "x.piece", "x.n").join(words.select("piece", "tokens"), "piece")
    parts = rows.select("row", "id", "n_bytes", F.col("known").alias("n_tokens"))
    parts = parts.unionAll(rare.select("row", F.lit(None).cast("long"), F.lit(0).cast("long"), F.col("n") * F.col("tokens")))
    return parts.groupBy("row").agg(F.max("id").alias("id"), F.sum("n_bytes").alias("n_bytes"), F.sum("n_tokens").alias("n_tokens")).drop("row")
