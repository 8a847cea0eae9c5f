"""Secret scans, in DataFrame functions only: patterns, then sliding-window entropy.

A pattern's matches are bracketed with noncharacters by one replacement; the
pieces between brackets give the code point positions.  Candidate strings for
the entropy are long runs of token characters that hold a digit and a letter.
For each character class, one fold over a candidate's characters keeps the
counts of the last ``WINDOW`` characters of the class, five bits each in a few
longs: the incoming and the outgoing character change one count each and the sum
of c * log2(c) by table entries, in millionths of a bit, so results are integers.  A candidate whose window reaches a class's
entropy adds a span, unless the allow list knows it.  Patterns' spans are cut out
of it, and the pieces left that hold such a window stay.

Defined results: null texts count as empty and have no spans; noncharacters
U+FDD0 to U+FDD2 of a text are read as another character, which moves nothing;
repeated rows are scanned each; a very long text, candidate or row of matches is
scanned whole, in time that grows little more than in proportion; an empty table
gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cutloom.llm.common import let

_OPEN, _MIDDLE, _CLOSE = "﷐", "﷑", "﷒"


@dataclass(frozen=True)
class Pattern:
    """``secret`` after ``lead``; a match counts if the secret (``whole``: all of it) has ``least`` characters."""

    kind: str
    lead: str
    secret: str
    least: int


#: Fixed values, in the order of kinds.
PATTERNS = [
    Pattern("assign", r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?""", r"[A-Za-z0-9+/_.=-]+", 6),
    Pattern("access", "", r"AKIA[A-Z0-9]+", 20),
    Pattern("hex", "", r"[0-9a-f]+", 24),
]

WINDOW = 20
CANDIDATE = r"[A-Za-z0-9+/_=-]{20,}"
#: Fixed values: (class, its characters, least entropy of a window in thousandths of a bit).
CLASSES = [("hexadecimal", "0123456789abcdefABCDEF", 3000), ("base64", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-", 3800)]
#: Candidates that are no secrets.
ALLOWED = [
    r"^[0-9A-Fa-f]{8}-[0-9A-Fa-f]{4}-[0-9A-Fa-f]{4}-[0-9A-Fa-f]{4}-[0-9A-Fa-f]{12}$",
    r"(?i:example|placeholder|lorem|xxxxx|abcdefgh|12345678)",
    r"^[a-z]+([-_/][a-z]+)*[-_/]?[0-9]{1,4}$",
    r"^[0-9+/_=-]+$",
]
ENTROPY = "entropy"
_SPANS = "array<struct<start:int,kind:int,end:int>>"


def _weigh(c: int) -> int:
    return round(1e6 * c * math.log2(c)) if c > 1 else 0


def clean(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), f"[{_OPEN}-{_CLOSE}]", "�")


def _pieces(text: Column, lead: str, secret: str) -> Column:
    """Array of pieces: the text before the first match, then lead, _MIDDLE, secret, _CLOSE and what follows."""
    return F.split(F.regexp_replace(text, f"({lead})({secret})", f"{_OPEN}$1{_MIDDLE}$2{_CLOSE}"), _OPEN)


CHUNK = 128


def running(values: Column, op: Callable[[Column, Column], Column]) -> Column:
    """For each of an array of longs: ``op`` over all before it, from 0.

    Chunks are folded alone and then shifted by what lies before them, since a
    fold that appends copies all it has: n * CHUNK / 2 steps instead of n * n / 2.
    """
    zero = F.lit(0).cast("long")

    def fold(items: Column, start: Column) -> Column:
        first = F.struct(start.alias("at"), F.array().cast("array<bigint>").alias("out"))
        return F.aggregate(items, first, lambda a, x: F.struct(op(a["at"], x).alias("at"), F.concat(a["out"], F.array(a["at"])).alias("out")), lambda a: a["out"])

    chunks = F.transform(F.sequence(F.lit(0), F.greatest(F.ceil(F.size(values) / CHUNK).cast("int") - 1, F.lit(0))), lambda k: F.slice(values, k * CHUNK + 1, CHUNK))

    def shifted(c: Column) -> Column:
        return let(fold(F.transform(c, lambda x: F.aggregate(x, zero, op)), zero), lambda heads: F.flatten(F.transform(c, lambda x, i: fold(x, F.get(heads, i)))))

    return let(chunks, shifted)


def _matches(text: Column, lead: str, secret: str) -> Column:
    """array<struct<start, end, secret>> of all matches, by position."""
    def walk(p: Column) -> Column:
        rest = F.slice(p, 2, F.greatest(F.size(p) - 1, F.lit(0)))

        def placed(before: Column) -> Column:
            def one(x: Column, i: Column) -> Column:
                start = (F.length(p[0]) + F.get(before, i)).cast("int")
                match = F.substring_index(x, _CLOSE, 1)
                return F.struct(start.alias("start"), (start + F.length(match) - 1).alias("end"), F.substring_index(match, _MIDDLE, -1).alias("secret"))

            return F.transform(rest, one)

        return let(running(F.transform(rest, lambda x: (F.length(x) - 2).cast("long")), lambda a, x: a + x), placed)

    none = F.array().cast("array<struct<start:int,end:int,secret:string>>")
    return F.when(text.rlike(f"{lead}{secret}"), let(_pieces(text, lead, secret), walk)).otherwise(none)


def pattern_spans(text: Column, kind: int, pattern: Pattern) -> Column:
    if pattern.lead:
        found = F.filter(_matches(text, pattern.lead, pattern.secret), lambda m: F.length(m["secret"]) >= pattern.least)
    else:  # a run is maximal, so its length can be asked of the pattern itself
        stem, tail = pattern.secret[:-1].split("[", 1)
        found = _matches(text, "", f"{stem}[{tail}{{{pattern.least - len(stem)},}}")
    return F.transform(found, lambda m: F.struct(m["start"].alias("start"), F.lit(kind).alias("kind"), m["end"].alias("end"))).cast(_SPANS)


_PER_LONG = 12  # counts of five bits


def entropy_extent(chars: Column, alphabet: str, least: int) -> Column:
    """struct<first, last> of an array of characters: from the first to the last window of the class that reaches ``least``; first is -1 for none."""
    gain = F.array(*[F.lit(_weigh(c + 1) - _weigh(c)).cast("bigint") for c in range(WINDOW + 1)])
    limit = math.floor(1e6 * WINDOW * math.log2(WINDOW)) - 1000 * WINDOW * least
    none = F.array_repeat(F.lit(0).cast("long"), -(-len(alphabet) // _PER_LONG))
    # a character's place: the long that holds its count, times 64, and the bit where it starts
    place = {ord(c): i // _PER_LONG * 64 + i % _PER_LONG * 5 for i, c in enumerate(alphabet)}
    table = F.array(*[F.lit(place.get(c, -1)) for c in range(128)])
    slot, bit = lambda k: F.shiftright(k, 6), lambda k: k.bitwiseAND(63)
    unit = lambda k, j: F.when(slot(k) == j, F.call_function("shiftleft", F.lit(1).cast("long"), bit(k))).otherwise(F.lit(0).cast("long"))

    def step(a: Column, x: Column) -> Column:
        count = lambda k: F.call_function("shiftright", F.get(a["counts"], slot(k)), bit(k)).bitwiseAND(31).cast("int")
        k, o, full = x["k"], x["o"], a["run"] >= WINDOW
        grown = a["sum"] + F.get(gain, count(k))
        total = F.when(full, grown - F.get(gain, count(o) + F.when(o == k, 0).otherwise(-1))).otherwise(grown)

        def moved(t: Column) -> Column:
            hit = (a["run"] + 1 >= WINDOW) & (t <= limit)
            counts = F.when(full, F.transform(a["counts"], lambda w, j: w + unit(k, j) - unit(o, j))).otherwise(F.transform(a["counts"], lambda w, j: w + unit(k, j)))
            return F.struct(counts.alias("counts"), t.alias("sum"), (a["run"] + 1).alias("run"), (a["at"] + 1).alias("at"), F.when(hit & (a["first"] < 0), a["at"] - WINDOW + 1).otherwise(a["first"]).alias("first"), F.when(hit, a["at"] + 1).otherwise(a["last"]).alias("last"))

        reset = F.struct(none.alias("counts"), F.lit(0).cast("long").alias("sum"), F.lit(0).alias("run"), (a["at"] + 1).alias("at"), a["first"].alias("first"), a["last"].alias("last"))
        return F.when(k < 0, reset).otherwise(let(total, moved))

    first = F.struct(none.alias("counts"), F.lit(0).cast("long").alias("sum"), F.lit(0).alias("run"), F.lit(0).alias("at"), F.lit(-1).alias("first"), F.lit(-1).alias("last"))

    def folded(codes: Column) -> Column:
        pairs = F.transform(codes, lambda k, i: F.struct(k.alias("k"), F.get(codes, i - WINDOW).alias("o")))
        return F.aggregate(pairs, first, step, lambda a: F.struct(a["first"].alias("first"), a["last"].alias("last")))

    return let(F.transform(chars, lambda c: F.coalesce(F.get(table, F.ascii(c)), F.lit(-1))), folded)


def candidates(text: Column, allowed: list[str] = ALLOWED) -> Column:
    """array<struct<at, chars, first, last>>: the candidate strings with a window of high entropy, and its extent in the text."""
    found = _matches(text, "", CANDIDATE)
    found = F.filter(found, lambda m: m["secret"].rlike("[0-9]") & m["secret"].rlike("[A-Za-z]"))
    if allowed:
        found = F.filter(found, lambda m: ~m["secret"].rlike("|".join(f"(?:{x})" for x in allowed)))

    def extents(m: Column) -> Column:
        def of(chars: Column) -> Column:
            each = F.array(*[entropy_extent(chars, alphabet, least) for _, alphabet, least in CLASSES])
            hit = F.struct(m["start"].alias("at"), chars.alias("chars"))
            return let(F.filter(each, lambda e: e["first"] >= 0), lambda e: F.when(F.size(e) > 0, F.struct(hit["at"].alias("at"), hit["chars"].alias("chars"), (m["start"] + F.array_min(F.transform(e, lambda x: x["first"]))).alias("first"), (m["start"] + F.array_max(F.transform(e, lambda x: x["last"]))).alias("last"))))

        return let(F.split(m["secret"], ""), of)

    return F.filter(F.transform(found, extents), lambda s: s.isNotNull())


def _first_index(spans: Column, test: Callable[[Column], Column]) -> Column:
    """The first index of a span for which ``test`` holds, as it does for all after it; by halving."""
    first = F.struct(F.lit(0).alias("low"), F.size(spans).alias("high"))

    def step(a: Column, _: Column) -> Column:
        middle = F.shiftright(a["low"] + a["high"], 1)
        here = test(F.get(spans, middle))
        return F.when(a["low"] >= a["high"], a).otherwise(F.struct(F.when(here, a["low"]).otherwise(middle + 1).alias("low"), F.when(here, middle).otherwise(a["high"]).alias("high")))

    return F.aggregate(F.sequence(F.lit(0), F.ceil(F.log2(F.size(spans) + 1.0)).cast("int")), first, step, lambda a: a["low"])


def _touching(c: Column, spans: Column) -> Column:
    """The spans of one pattern, which are in order and apart, that touch the extent of a candidate."""
    low = _first_index(spans, lambda x: x["end"] > c["first"])
    return F.when(F.size(spans) == 0, spans).otherwise(let(low, lambda at: F.slice(spans, at + 1, F.greatest(_first_index(spans, lambda x: x["start"] >= c["last"]) - at, F.lit(0)))))


def _outside(c: Column, kind: int, base: Column) -> Column:
    """The pieces of a candidate's extent that no span of ``base`` (sorted) touches and that hold a window of high entropy."""
    def with_piece(a: Column, end: Column) -> Column:
        return F.concat(a["out"], F.array(F.struct(a["at"].alias("start"), F.lit(kind).alias("kind"), end.alias("end"))))

    def step(a: Column, x: Column) -> Column:
        return F.struct(F.greatest(a["at"], x["end"]).alias("at"), F.when(x["start"] > a["at"], with_piece(a, x["start"])).otherwise(a["out"]).alias("out"))

    first = F.struct(c["first"].alias("at"), F.array().cast(_SPANS).alias("out"))
    pieces = F.aggregate(base, first, step, lambda a: F.when(a["at"] < c["last"], with_piece(a, c["last"])).otherwise(a["out"]))

    def hot(s: Column) -> Column:
        part = F.slice(c["chars"], s["start"] - c["at"] + 1, s["end"] - s["start"])
        return (s["end"] - s["start"] >= WINDOW) & let(part, lambda x: F.exists(F.array(*[entropy_extent(x, alphabet, least)["first"] for _, alphabet, least in CLASSES]), lambda f: f >= 0))

    return F.when(F.size(base) == 0, F.array(F.struct(c["first"].alias("start"), F.lit(kind).alias("kind"), c["last"].alias("end")))).otherwise(F.filter(pieces, hot))


def scan(text: Column) -> Column:
    """struct<base, all>: sorted spans of the patterns, and with those of the entropy."""
    def of(t: Column) -> Column:
        kinds = F.array(*[pattern_spans(t, i, p) for i, p in enumerate(PATTERNS)])

        def with_kinds(k: Column) -> Column:
            touching = lambda c: F.sort_array(F.concat(*[_touching(c, F.get(k, F.lit(i))) for i in range(len(PATTERNS))]))
            fresh = F.flatten(F.transform(candidates(t), lambda c: let(touching(c), lambda b: _outside(c, len(PATTERNS), b))))
            return let(F.sort_array(F.flatten(k)), lambda b: F.struct(b.alias("base"), F.sort_array(F.concat(b, fresh)).alias("all")))

        return let(kinds, with_kinds)

    return let(clean(text), of)


def shown(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    names = F.array(*[F.lit(p.kind) for p in PATTERNS], F.lit(ENTROPY))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def scanned(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with __spans (base and all)."""
    return docs.withColumn("__spans", scan(F.col(text_col)))


def redacted(docs: DataFrame) -> DataFrame:
    """``docs`` (documents columns) with each secret replaced by its kind in brackets; n_chars follows."""
    names = F.array(*[F.lit(f"[{p.kind}]") for p in PATTERNS], F.lit(f"[{ENTROPY}]"))

    def told(spans: Column) -> Column:
        ends = F.transform(spans, lambda s: s["end"].cast("long"))

        def shortened(chars: Column) -> Column:
            def joined(before: Column) -> Column:
                # a span that begins inside an earlier one belongs to it
                part = lambda s, at: F.when(s["start"] >= at, F.concat(F.array_join(F.slice(chars, at + 1, s["start"] - at), ""), F.get(names, s["kind"]))).otherwise("")
                last = F.array_max(ends).cast("int")
                return F.concat(F.array_join(F.transform(spans, lambda s, i: part(s, F.get(before, i).cast("int"))), ""), F.array_join(F.slice(chars, last + 1, F.greatest(F.size(chars) - last, F.lit(0))), ""))

            return let(running(ends, lambda a, x: F.greatest(a, x)), joined)

        return let(F.split(F.col("text"), ""), shortened)

    columns = docs.columns
    packed = docs.select(F.struct(*columns).alias("row"), F.col("text"))
    marked = scanned(packed)
    found = F.size("__spans.all") > 0
    out = marked.withColumn("clean", F.when(found, told(F.col("__spans.all"))).otherwise(F.col("text")))
    new = {"text": F.col("clean")}
    if "n_chars" in columns:
        new["n_chars"] = F.when(found, F.length("clean").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("row.n_chars"))
    return out.select(*[new.get(c, F.col("row")[c]).alias(c) for c in columns])
