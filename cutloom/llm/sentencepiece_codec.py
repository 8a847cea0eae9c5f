"""SentencePiece encoding and decoding with shared prefixes.

Texts are cut into marked words: a run of the space mark and the characters
after it (no piece of the vocabulary crosses such a cut; that is checked when a
model is loaded).  A task sorts the distinct marked words of a batch, which
lays out their trie in depth-first order, and walks it with a stack of forward
states, so the states of a common prefix are computed once.

A forward state is, for unigram models, the best score of a prefix and its
last piece.  For BPE models (the file at hand) the best sum of scores is not
what the library returns: it merges by rank.  There the state is the last piece
of the prefix's own encoding.  That encoding is the state ``len(piece)``
characters earlier plus the one suffix piece that stays apart from the piece
before it when the two are merged by rank; so the walk, the stack and the
back-pointers are those of the Viterbi traversal, and results equal the
library's.

Defined results: null texts count as empty, and empty texts have no pieces;
characters outside the vocabulary become byte pieces; a literal mark U+2581
reads as a space after decoding, as in the library.
"""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutloom.llm.common import gathered

MARK = "▁"
_SHORT = (2, 1)
_MARKED_WORD = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+")


class Codec:
    """Pieces of one model file; encodes marked words."""

    def __init__(self, pieces: dict[str, int], scores: list[float], bytes_at: int | None, unknown: int = 0, kind: str = "bpe", dummy_prefix: bool = True):
        self.pieces, self.scores, self.kind, self.unknown, self.bytes_at, self.dummy = pieces, scores, kind, unknown, bytes_at, dummy_prefix
        self.longest = max(map(len, pieces), default=1)
        crossing = [p for p in pieces if MARK in p.lstrip(MARK)]
        if crossing:
            raise ValueError(f"pieces cross marked words: {crossing[:3]}")
        self.apart: dict[int, bool] = {}
        self.known: dict[str, bytes] = {}
        self.by_id: dict[int, str] = {i: p for p, i in pieces.items()}
        self.lengths = {i: len(p) for p, i in pieces.items()}
        self.raw = [self.by_id.get(i, "").replace(MARK, " ").encode() for i in range(len(scores))]
        if bytes_at is not None:
            self.raw[bytes_at: bytes_at + 256] = [bytes([b]) for b in range(256)]
        self.worst = min(scores, default=0.0)
        #: lengths, longest first, of the pieces that may end with the key
        ends: dict[str, set[int]] = {}
        for p in pieces:
            if len(p) > 2:
                ends.setdefault(p[-3:], set()).add(len(p))
        self.sizes = {k: (*sorted(v, reverse=True), *_SHORT) for k, v in ends.items()}

    def merged(self, text: str) -> list[str]:
        """Merge the best scored adjacent pair, leftmost first, until none is a piece."""
        parts = list(text)
        while True:
            best, at = None, -1
            for i in range(len(parts) - 1):
                j = self.pieces.get(parts[i] + parts[i + 1])
                if j is not None and (best is None or self.scores[j] > best):
                    best, at = self.scores[j], i
            if at < 0:
                return parts
            parts[at: at + 2] = [parts[at] + parts[at + 1]]

    def stays_apart(self, left: int, right: int) -> bool:
        """Whether merging the text of two pieces gives these two."""
        if len(self.apart) > 1_000_000:
            self.apart.clear()
        a, b = self.by_id[left], self.by_id[right]
        known = self.apart[left << 32 | right] = self.merged(a + b) == [a, b]
        return known

    def grow_unigram(self, word: str, start: int, last: list[int], best: list[float]) -> None:
        """Append the states of word[:i + 1] from ``start`` on: the last piece of the best path and its score."""
        for i in range(start, len(word)):
            top, found = best[i] + self.worst - 10.0, -1
            for size in range(1, min(i + 1, self.longest) + 1):
                j = self.pieces.get(word[i + 1 - size: i + 1])
                if j is not None and best[i + 1 - size] + self.scores[j] >= top:
                    top, found = best[i + 1 - size] + self.scores[j], j
            best.append(top)
            last.append(found)

    def grow_bpe(self, word: str, start: int, last: list[int]) -> None:
        """Append the states of word[:i + 1] from ``start`` on: its last piece, or -1 for a character outside the vocabulary."""
        pieces, apart, sizes = self.pieces, self.apart, self.sizes
        for i in range(start, len(word)):
            found = -1
            for size in sizes.get(word[i - 2: i + 1], _SHORT) if i > 1 else _SHORT:
                at = i - size
                if at < -1:
                    continue
                j = pieces.get(word[at + 1: i + 1])
                if j is None:
                    continue
                before = last[at] if at >= 0 else -1
                if before < 0:
                    if self.whole(j):
                        found = j
                        break
                    continue
                known = apart.get(before << 32 | j)
                if known is None:
                    known = self.stays_apart(before, j)
                if known:
                    found = j
                    break
            last.append(found)

    @lru_cache(maxsize=65536)  # noqa: B019
    def whole(self, j: int) -> bool:
        return self.merged(self.by_id[j]) == [self.by_id[j]]

    def walk(self, words: list[str]) -> Iterator[bytes]:
        """Encodings of sorted distinct words as little-endian int32 ids, with byte pieces for characters outside the vocabulary."""
        last: list[int] = []
        best: list[float] = [0.0]
        before = ""
        unigram, lengths = self.kind == "unigram", self.lengths
        for word in words:
            shared, top = 0, min(len(before), len(word))
            while shared < top and before[shared] == word[shared]:
                shared += 1
            del last[shared:]
            del best[shared + 1:]
            if unigram:
                self.grow_unigram(word, shared, last, best)
            else:
                self.grow_bpe(word, shared, last)
            before = word
            ids = []
            i = len(word) - 1
            while i >= 0:
                j = last[i]
                if j >= 0:
                    ids.append(j)
                    i -= lengths[j]
                else:
                    ids += [self.bytes_at + b for b in reversed(word[i].encode())] if self.bytes_at is not None else [self.unknown]
                    i -= 1
            ids.reverse()
            yield array("i", ids).tobytes()

    def marked(self, text: str) -> list[str]:
        """The marked words of a text, in order."""
        if not text:
            return []
        return _MARKED_WORD.findall((MARK if self.dummy else "") + text.replace(" ", MARK))

    def decode(self, ids: list[int]) -> str:
        """The text of ids; runs of byte pieces are read as UTF-8."""
        text = b"".join(map(self.raw.__getitem__, ids)).decode("utf-8", "replace")
        return text[1:] if self.dummy and text.startswith(" ") else text


@lru_cache(maxsize=2)
def load(path: str) -> Codec:
    """The codec of a .model file; its normaliser must leave texts as they are."""
    from sentencepiece import sentencepiece_model_pb2

    model = sentencepiece_model_pb2.ModelProto()
    with open(path, "rb") as f:
        model.ParseFromString(f.read())
    spec = model.normalizer_spec
    if spec.precompiled_charsmap or spec.remove_extra_whitespaces or not spec.escape_whitespaces:
        raise ValueError("models with a normaliser are not handled")
    normal = {p.piece: i for i, p in enumerate(model.pieces) if p.type == 1}
    bytes_at = next((i for i, p in enumerate(model.pieces) if p.type == 6 and p.piece == "<0x00>"), None)
    kind = {1: "unigram", 2: "bpe"}[model.trainer_spec.model_type]
    unknown = next((i for i, p in enumerate(model.pieces) if p.type == 2), 0)
    return Codec(normal, [p.score for p in model.pieces], bytes_at, unknown, kind, spec.add_dummy_prefix)


def encode_texts(codec: Codec, texts: list[str], most: int = 400_000) -> Iterator[np.ndarray]:
    """The ids of each text; the distinct marked words that the codec hasn't met are walked as one trie.

    It remembers ``most`` words, or those of the texts at hand where they are more.
    """
    cut = [codec.marked(t) for t in texts]
    wanted = set().union(*cut)
    new = sorted(wanted - codec.known.keys())
    if len(codec.known) + len(new) > most:
        codec.known = {w: codec.known[w] for w in wanted if w in codec.known}
    known = codec.known
    known.update(zip(new, codec.walk(new)))
    for words in cut:
        yield np.frombuffer(b"".join(map(known.__getitem__, words)), "<i4")


def encoded(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids array<int>, decoded string) for each row."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = load(path)
        for rows in gathered(batches, 2 << 20):
            ids = list(encode_texts(codec, rows.column("text").to_pylist()))
            offsets = np.cumsum([0, *map(len, ids)])
            column = pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(np.concatenate(ids)))
            yield pa.RecordBatch.from_arrays([rows.column("id").combine_chunks(), column, pa.array([codec.decode(one.tolist()) for one in ids], pa.string())], ["id", "ids", "decoded"])

    return _texts(docs, id_col, text_col).mapInArrow(run, "id long, ids array<int>, decoded string")


def digests(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_pieces, ids_hash, round_trip): the encoding's length, XXH64 of its ids as little-endian int32, and whether decoding gives the text back."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = load(path)
        for rows in gathered(batches, 2 << 20):
            texts = rows.column("text").to_pylist()
            n, h, same = [], [], []
            for text, ids in zip(texts, encode_texts(codec, texts)):
                n.append(len(ids))
                h.append(xxhash.xxh64_intdigest(ids.tobytes()))
                same.append(codec.decode(ids.tolist()) == text)
            yield pa.RecordBatch.from_arrays([rows.column("id").combine_chunks(), pa.array(n, pa.int64()), pa.array(np.array(h, np.uint64).view(np.int64)), pa.array(same, pa.bool_())], ["id", "n_pieces", "ids_hash", "round_trip"])

    return _texts(docs, id_col, text_col).mapInArrow(run, "id long, n_pieces long, ids_hash long, round_trip boolean")


def _texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
