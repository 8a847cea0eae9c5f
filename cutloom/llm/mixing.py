"""Mixing sources to target weights, in DataFrame functions only.

The token budget goes down a tree of levels (domain, language, source).  A
node's share is limited by what its subtree can give, its tokens times the
most epochs; what a child can't take goes to its siblings by weight, and only
when a whole subtree is short does the rest reach the siblings of its parent.
At each node that is water filling, which has a closed form over the children
in order of limit / weight; so each level is one window, without iteration.

A leaf with budget b and h tokens gives floor(b / h) whole epochs and, of the
next, the longest prefix within the rest, in an order by a seeded hash of the
document id and the epoch.  The prefix is found in two steps, hash buckets
first and then the one bucket in which it ends, so a leaf that holds a third of
all rows never meets in one task.  Joins of rows with their leaf are salted.
Words are counted once; the counts are stored in the shared folder.

Defined results: null or empty texts have no tokens and are kept once if their
leaf has none; null level values are the node ``none``; rows with equal ids
stand or fall together; a very long text counts whole; an empty table gives no
rows; columns of the input may have any names, as it travels in one struct.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cutloom.llm.common import SPACE_PATTERN, shuffle_partitions, stored

#: The weights of the query and the pipeline; others weigh 1.
WEIGHTS = {"domain": {"web": 4, "news": 3, "forum": 2, "other": 1}, "lang": {"en": 4, "de": 2, "fr": 2, "es": 2}, "source": {}}
#: 2^BITS hash buckets a leaf: the one bucket that a window sorts holds that share of the leaf's rows.
SEED, EPOCHS, SHARE, BITS = 17, 2, 800, 16
LEVELS = ("domain", "lang", "source")


def n_words(text: Column) -> Column:
    """Words between ASCII white space."""
    t = F.coalesce(text, F.lit(""))
    return (F.size(F.split(t, SPACE_PATTERN)) - t.rlike("^" + SPACE_PATTERN).cast("int") - t.rlike(SPACE_PATTERN + r"\z").cast("int") - (t == "").cast("int")).cast("long")


def domain(source: Column) -> Column:
    """The given tables have no domain; sources are dealt to four by their number."""
    k = F.coalesce(F.try_to_number(F.regexp_extract(F.coalesce(source, F.lit("")), "([0-9]{1,9})$", 1), F.lit("999999999")).cast("long"), F.lit(99).cast("long"))
    return F.when(k < 5, "web").when(k < 10, "news").when(k < 15, "forum").otherwise("other")


def levels_of(docs: DataFrame) -> DataFrame:
    """``docs`` with the tree's columns __domain, __lang and __source."""
    return docs.withColumn("__domain", domain(F.col("source"))).withColumn("__lang", F.coalesce("lang", F.lit("none"))).withColumn("__source", F.coalesce("source", F.lit("none")))


def _weight(level: str, weights: dict[str, dict[str, int]]) -> Column:
    w = F.lit(1)
    for name, value in weights.get(level, {}).items():
        w = F.when(F.col(f"__{level}") == name, value).otherwise(w)
    return w.cast("long")


def budgets(leaves: DataFrame, weights: dict[str, dict[str, int]], share: int, epochs: int, levels: tuple[str, ...] = LEVELS) -> DataFrame:
    """Leaves (__level columns, have) with their budget in tokens; ``share`` thousandths of all tokens are asked for."""
    names = [f"__{x}" for x in levels]
    total = leaves.agg(F.coalesce(F.sum("have"), F.lit(0)).alias("__t")).select(F.floor(F.col("__t") * share / 1000).cast("long").alias("budget"))
    nodes = total.select("budget", F.lit(1).alias("__root"))
    for depth, level in enumerate(levels):
        keys, parent = names[: depth + 1], names[:depth]
        children = leaves.groupBy(*keys).agg((F.sum("have") * epochs).alias("most")).withColumn("w", _weight(level, weights)).withColumn("__root", F.lit(1))
        on = [*parent, "__root"]
        down = children.join(nodes, on)
        # children in order of limit / weight: full ones come first
        order = Window.partitionBy(*on).orderBy((F.col("most") / F.col("w")).asc(), keys[-1])
        before = order.rowsBetween(Window.unboundedPreceding, -1)
        after = order.rowsBetween(0, Window.unboundedFollowing)
        d = "decimal(38,0)"
        placed = down.withColumn("c", F.coalesce(F.sum("most").over(before), F.lit(0))).withColumn("s", F.sum("w").over(after))
        placed = placed.withColumn("full", F.col("most").cast(d) * F.col("s") <= F.col("w").cast(d) * (F.col("budget") - F.col("c")))
        every = Window.partitionBy(*on)
        spent = F.sum(F.when(F.col("full"), F.col("most")).otherwise(0)).over(every)
        rest = F.sum(F.when(F.col("full"), 0).otherwise(F.col("w"))).over(every)
        placed = placed.withColumn("spent", spent).withColumn("rest", rest)
        part = F.expr("CAST(w AS DECIMAL(19,0)) * CAST(budget - spent AS DECIMAL(19,0)) div rest")
        nodes = placed.select(*keys, "__root", F.when(F.col("full"), F.col("most")).otherwise(part).cast("long").alias("budget"))
    return nodes.drop("__root")


def _order(epoch: Column, id_col: str, seed: int) -> Column:
    return F.xxhash64(F.lit(seed).cast("long"), epoch.cast("long"), F.col(id_col).cast("long"))


def _with_leaf(rows: DataFrame, plan: DataFrame, names: list[str], how: str = "inner") -> DataFrame:
    """``rows`` joined to ``plan`` by leaf.  A leaf's row is repeated for as many salts as there are
    shuffle partitions, and its rows are dealt to them in turn, so a hot leaf is no task of its own."""
    salts = shuffle_partitions(rows.sparkSession)
    dealt = rows.withColumn("__leaf_salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts)).cast("int"))
    each = plan.withColumn("__leaf_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return dealt.join(each, [*names, "__leaf_salt"], how).drop("__leaf_salt")


def decisions(docs: DataFrame, weights=WEIGHTS, share: int = SHARE, epochs: int = EPOCHS, seed: int = SEED, bits: int = BITS, id_col: str = "doc_id", tokens: Column | None = None) -> DataFrame:
    """For each leaf: __epochs (whole ones), and __bucket and __last, where the prefix of the next ends; also __have and __budget."""
    names = [f"__{x}" for x in LEVELS]
    packed = docs.select(F.col("source"), F.col("lang"), F.col(id_col).alias("__id"), (n_words(F.col("text")) if tokens is None else tokens).alias("__n"))
    rows = stored(levels_of(packed).select(*names, "__id", "__n"))
    leaves = rows.groupBy(*names).agg(F.sum("__n").alias("have"))
    plan = budgets(leaves, weights, share, epochs).join(leaves, names)
    whole = F.when(F.col("have") > 0, F.floor(F.col("budget") / F.when(F.col("have") > 0, F.col("have")))).otherwise(1).cast("long")
    plan = plan.select(*names, F.col("have").alias("__have"), F.col("budget").alias("__budget"), whole.alias("__epochs")).withColumn("__rest", F.when(F.col("__have") > 0, F.col("__budget") - F.col("__epochs") * F.col("__have")).otherwise(0))
    # every row's place in every epoch that could be the last one
    placed = _with_leaf(rows, plan.select(*names, "__epochs", "__rest"), names).withColumn("o", _order(F.col("__epochs"), "__id", seed)).withColumn("b", _bucket(F.col("o"), bits))
    buckets = placed.groupBy(*names, "__rest", "b").agg(F.sum("__n").alias("t"))
    run = Window.partitionBy(*names).orderBy("b")
    cut = buckets.withColumn("before", F.sum("t").over(run) - F.col("t")).where("before <= __rest AND __rest < before + t").select(*names, F.col("b").alias("__bucket"), "before")
    inside = _with_leaf(placed, cut, names).where("b = __bucket").withColumn("sum", F.sum("__n").over(Window.partitionBy(*names).orderBy("o")))
    last = inside.where("before + sum <= __rest").groupBy(*names).agg(F.max("o").alias("__last"))
    return plan.join(cut.select(*names, "__bucket"), names, "left").join(last, names, "left").select(*names, "__have", "__budget", "__epochs", "__bucket", "__last")


def _bucket(o: Column, bits: int) -> Column:
    return (F.shiftright(o, 64 - bits) + (1 << (bits - 1))).cast("int")


def copies(docs: DataFrame, plan: DataFrame, seed: int = SEED, bits: int = BITS, id_col: str = "doc_id") -> DataFrame:
    """(row: the whole input row as a struct, __domain, __lang, __source, __copies): whole epochs, and one more in the prefix."""
    names = [f"__{x}" for x in LEVELS]
    packed = levels_of(docs.select(F.struct(*docs.columns).alias("row"), F.col("source"), F.col("lang"), F.col(id_col).alias("__id")))
    rows = _with_leaf(packed.select("row", "__id", *names), plan.select(*names, "__epochs", "__bucket", "__last"), names, "left")
    o = _order(F.col("__epochs"), "__id", seed)
    b = _bucket(o, bits)
    extra = F.coalesce((b < F.col("__bucket")) | ((b == F.col("__bucket")) & (o <= F.col("__last"))), b < F.col("__bucket"), F.lit(False))
    return rows.select("row", *names, (F.coalesce("__epochs", F.lit(0)) + extra.cast("long")).alias("__copies"))


def mixed(docs: DataFrame, weights=WEIGHTS, share: int = SHARE, epochs: int = EPOCHS, seed: int = SEED) -> DataFrame:
    """The rows of ``docs`` (documents columns), each as often as it was drawn."""
    drawn = copies(docs, decisions(docs, weights, share, epochs, seed), seed).where("__copies > 0")
    return drawn.select("row", F.explode(F.sequence(F.lit(1).cast("long"), F.col("__copies"))).alias("__k")).select("row.*")
