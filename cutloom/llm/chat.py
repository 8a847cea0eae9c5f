"""Chat formatting from every participant's perspective, in DataFrame functions only.

For each participant of a conversation the dialogue is rendered with that
speaker as the assistant, everyone else as a user with their name, and system
turns as they are; the mask holds the spans (code points, end exclusive) of
what the assistant says, which is what a loss is taken on.

A dialogue is rendered in pieces of ``SPAN`` turn numbers, so a conversation of
any length never meets in one row; piece k holds turns k * SPAN to
(k + 1) * SPAN - 1.  Where numbers are null or repeated a piece could hold any
number of turns, so it is cut into parts of at most ``SPAN`` turns, in order.
Pieces and parts of a perspective laid end to end are its whole dialogue.

Defined results: null texts are empty, a null role is the participant
``unknown``, turns with a null number come first (piece -1); turns with one
number are ordered by role and text, and repeated rows are rendered each; a
conversation of system turns alone has no participant and no rows; a null
conversation id is one more conversation; an empty table gives no rows; a very
long text is one turn of its part.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cutloom.llm.common import let

SPAN = 256
#: The template.
SYSTEM, ASSISTANT, USER, END = "<|system|>\n", "<|assistant|>\n", "<|user:{}|>\n", "<|end|>\n"

_STATE = "struct<at:bigint,out:array<struct<start:bigint,end:bigint>>>"


def _head(role: Column, speaker: Column) -> Column:
    before, after = USER.split("{}")
    return F.when(role == "system", SYSTEM).when(role == speaker, ASSISTANT).otherwise(F.concat(F.lit(before), role, F.lit(after)))


def perspectives(turns: DataFrame, span: int = SPAN) -> DataFrame:
    """(conv_id, speaker, piece, part, n_turns, n_own, text, mask array<struct<start, end>>)."""
    rows = turns.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.withColumn("piece", F.coalesce(F.floor(F.col("turn") / span).cast("long"), F.lit(-1).cast("long")))
    place = F.row_number().over(Window.partitionBy("conv_id", "piece").orderBy("turn", "role", "text"))
    rows = rows.withColumn("part", F.floor((place - 1) / span).cast("long"))
    pieces = rows.groupBy("conv_id", "piece", "part").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    seats = rows.where("role <> 'system'").select("conv_id", F.col("role").alias("speaker")).distinct()
    joined = pieces.join(seats.withColumnRenamed("conv_id", "__conv"), F.col("conv_id").eqNullSafe(F.col("__conv"))).drop("__conv")

    def mask(parts: Column) -> Column:
        first = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:bigint,end:bigint>>").alias("out")).cast(_STATE)

        def step(a: Column, x: Column) -> Column:
            start = a["at"] + F.length(x["head"])
            end = start + F.length(x["text"])
            out = F.when(x["own"], F.concat(a["out"], F.array(F.struct(start.alias("start"), end.alias("end"))))).otherwise(a["out"])
            return F.struct((end + len(END)).alias("at"), out.alias("out")).cast(_STATE)

        return F.aggregate(parts, first, step, lambda a: a["out"])

    def render(parts: Column) -> Column:
        return F.struct(F.array_join(F.transform(parts, lambda x: F.concat(x["head"], x["text"], F.lit(END))), "").alias("text"), mask(parts).alias("mask"), F.size(F.filter(parts, lambda x: x["own"])).cast("long").alias("n_own"))

    parts = F.transform("turns", lambda t: F.struct(_head(t["role"], F.col("speaker")).alias("head"), t["text"].alias("text"), (t["role"] == F.col("speaker")).alias("own")))
    return joined.withColumn("r", let(parts, render)).select("conv_id", "speaker", "piece", "part", F.size("turns").cast("long").alias("n_turns"), F.col("r.n_own").alias("n_own"), F.col("r.text").alias("text"), F.col("r.mask").alias("mask"))


def digests(turns: DataFrame, span: int = SPAN) -> DataFrame:
    """perspectives() with the SHA-256 and length of the text and the mask as start:end, comma-joined."""
    shown = F.array_join(F.transform("mask", lambda m: F.concat_ws(":", m["start"].cast("string"), m["end"].cast("string"))), ",")
    return perspectives(turns, span).select("conv_id", "speaker", "piece", "part", "n_turns", "n_own", F.length("text").cast("long").alias("n_chars"), F.sha2("text", 256).alias("text_sha256"), shown.alias("mask"))


def oracle(span: int = SPAN) -> str:
    before, after = USER.split("{}")
    lit = lambda s: "'" + s.replace("\n", "' || chr(10) || '") + "'"
    return f"""
WITH t AS (SELECT conv_id, turn, coalesce(role, 'unknown') AS role, coalesce(text, '') AS text, coalesce(floor(turn / {span})::BIGINT, -1) AS piece FROM conversations),
s AS (SELECT DISTINCT conv_id, role AS speaker FROM t WHERE role <> 'system'),
u AS (SELECT *, ((row_number() OVER (PARTITION BY conv_id, piece ORDER BY turn NULLS FIRST, role, text) - 1) // {span})::BIGINT AS part FROM t),
x AS (SELECT t.*, speaker, role = speaker AS own, CASE WHEN role = 'system' THEN {lit(SYSTEM)} WHEN role = speaker THEN {lit(ASSISTANT)} ELSE {lit(before)} || role || {lit(after)} END AS head FROM u AS t JOIN s ON t.conv_id IS NOT DISTINCT FROM s.conv_id),
y AS (SELECT *, sum(length(head) + length(text) + {len(END)}) OVER w - length(text) - {len(END)} AS a, row_number() OVER w AS k FROM x WINDOW w AS (PARTITION BY conv_id, speaker, piece, part ORDER BY turn NULLS FIRST, role, text ROWS UNBOUNDED PRECEDING))
SELECT conv_id, speaker, piece, part, count(*)::BIGINT AS n_turns, count(*) FILTER (own)::BIGINT AS n_own, sum(length(head) + length(text) + {len(END)})::BIGINT AS n_chars,
  sha256(string_agg(head || text || {lit(END)}, '' ORDER BY k)) AS text_sha256,
  coalesce(string_agg(a::BIGINT || ':' || (a + length(text))::BIGINT, ',' ORDER BY k) FILTER (own), '') AS mask
FROM y GROUP BY conv_id, speaker, piece, part"""
