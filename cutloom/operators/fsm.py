"""Frequent labelled patterns of up to three edges by smallest domain.

All labelled patterns of a shape are handled in one pass, grouped by the labels
of their vertices.  ``fragments`` never makes whole matchings of the largest
shapes: a role's vertices follow from part rows and grouped counts.  Where the
graph fits a task and labels are few, these are numpy arrays (see labelled.py),
also for ``auto``; ``embeddings`` always makes the matchings.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from cutloom.operators import labelled
from cutloom.operators.graph import Graph
from cutloom.patterns.algebra import Pattern, automorphisms
from cutloom.patterns.catalogue import chain, clique, star

#: Shapes by number of edges, with names.
SHAPES = {1: [("edge", chain(2))], 2: [("chain3", Pattern.parse("01 02"))], 3: [("triangle", clique(3)), ("star3", star(3)), ("chain4", Pattern.parse("01 02 13"))]}


def _arcs(g: Graph, frequent: DataFrame | None) -> DataFrame:
    """arcs with labels; with ``frequent`` those whose label pair is frequent."""
    arcs = g.arcs.where("lu IS NOT NULL AND lv IS NOT NULL")
    if frequent is None:
        return arcs
    pairs = frequent.where("shape = 'edge'").select(F.col("l0").alias("lu"), F.col("l1").alias("lv"))
    pairs = pairs.unionAll(pairs.select(F.col("lv").alias("lu"), F.col("lu").alias("lv"))).distinct()
    return arcs.join(pairs, ["lu", "lv"], "left_semi").select("u", "v", "lu", "lv")


def _hop(arcs: DataFrame, a: int, b: int) -> DataFrame:
    return arcs.select(F.col("u").alias(f"m{a}"), F.col("v").alias(f"m{b}"), F.col("lu").alias(f"l{a}"), F.col("lv").alias(f"l{b}"))


def _whole(arcs: DataFrame, shape: str) -> DataFrame:
    """All matchings m0.., l0.. of a shape."""
    if shape == "edge":
        return _hop(arcs, 0, 1)
    if shape == "chain3":
        return _hop(arcs, 0, 1).join(_hop(arcs, 0, 2).drop("l0"), "m0").where("m1 <> m2")
    if shape == "triangle":
        return _whole(arcs, "chain3").join(arcs.select(F.col("u").alias("m1"), F.col("v").alias("m2")), ["m1", "m2"], "left_semi")
    if shape == "star3":
        return _whole(arcs, "chain3").join(_hop(arcs, 0, 3).drop("l0"), "m0").where("m1 <> m3 AND m2 <> m3")
    return _whole(arcs, "chain3").join(_hop(arcs, 1, 3).drop("l1"), "m1").where("m3 <> m0 AND m3 <> m2")


def _roles(rows: DataFrame, n: int) -> DataFrame:
    labels = [F.col(f"l{i}") for i in range(n)]
    x = F.explode(F.array(*[F.struct(F.lit(i).alias("role"), F.col(f"m{i}").alias("v")) for i in range(n)]))
    return rows.select(*labels, x.alias("x")).select(*[f"l{i}" for i in range(n)], "x.role", "x.v").distinct()


def _roles_by_fragments(arcs: DataFrame, shape: str) -> DataFrame | None:
    """(l0.., role, v) of the two tree shapes from counts by label: a vertex fills a role if enough other vertices remain."""
    by = arcs.groupBy("u", "lu", "lv").agg(F.count(F.lit(1)).alias("d"))  # d: neighbours of u with label lv
    if shape == "star3":
        # a centre needs, for each label, as many neighbours as there are leaves of it
        def leaf(i: int) -> DataFrame:
            return by.select(F.col("u"), F.col("lu").alias("l0"), F.col("lv").alias(f"l{i}"), F.col("d").alias(f"d{i}"))

        same = lambda i: sum((F.col(f"l{i}") == F.col(f"l{j}")).cast("int") for j in (1, 2, 3))
        centre = leaf(1).join(leaf(2), ["u", "l0"]).join(leaf(3), ["u", "l0"]).where((F.col("d1") >= same(1)) & (F.col("d2") >= same(2)) & (F.col("d3") >= same(3)))
        stars = centre.select("u", "l0", "l1", "l2", "l3")
        middle = stars.select("l0", "l1", "l2", "l3", F.lit(0).alias("role"), F.col("u").alias("v"))
        legs = [stars.join(arcs.select(F.col("u"), F.col("v").alias("leaf"), F.col("lv").alias(f"l{i}")), ["u", f"l{i}"]).select("l0", "l1", "l2", "l3", F.lit(i).alias("role"), F.col("leaf").alias("v")) for i in (1, 2, 3)]
        return reduce(DataFrame.unionAll, [middle, *legs]).distinct()
    if shape == "chain4":
        # edges 01 02 13, cut {0, 1}; leaf 2 hangs on 0 and leaf 3 on 1, and they must differ
        middle = arcs.select(F.col("u").alias("m0"), F.col("v").alias("m1"), F.col("lu").alias("l0"), F.col("lv").alias("l1"))
        at = lambda m, l, leaf: by.select(F.col("u").alias(m), F.col("lv").alias(leaf), F.col("d").alias(f"d{leaf}"))
        common = arcs.select(F.col("u").alias("m0"), F.col("v").alias("w"), F.col("lv").alias("lw")).join(arcs.select(F.col("u").alias("m1"), F.col("v").alias("w")), "w")
        shared = common.join(middle.select("m0", "m1"), ["m0", "m1"], "left_semi").groupBy("m0", "m1", "lw").agg(F.count(F.lit(1)).alias("t"))
        rows = middle.join(at("m0", "l0", "l2"), "m0").join(at("m1", "l1", "l3"), "m1").join(shared.select("m0", "m1", F.col("lw").alias("l2"), "t"), ["m0", "m1", "l2"], "left")
        rows = rows.withColumn("t", F.coalesce("t", F.lit(0))).withColumn("a", F.col("dl2") - (F.col("l2") == F.col("l1")).cast("int")).withColumn("b", F.col("dl3") - (F.col("l3") == F.col("l0")).cast("int"))
        # pairs (leaf of 0, leaf of 1) that differ: a * b, less the common neighbours where the labels agree
        rows = rows.where(F.col("a") * F.col("b") - F.when(F.col("l2") == F.col("l3"), F.col("t")).otherwise(0) > 0).persist()
        ends = [rows.select("l0", "l1", "l2", "l3", F.lit(0).alias("role"), F.col("m0").alias("v")), rows.select("l0", "l1", "l2", "l3", F.lit(1).alias("role"), F.col("m1").alias("v"))]
        for mine, far, leaf, other, role, count in (("m0", "m1", "l2", "l3", 2, "b"), ("m1", "m0", "l3", "l2", 3, "a")):
            legs = rows.join(arcs.select(F.col("u").alias(mine), F.col("v").alias("w"), F.col("lv").alias(leaf)), [mine, leaf]).where(F.col("w") != F.col(far))
            tied = arcs.select(F.col("u").alias(far), F.col("v").alias("w"), F.lit(1).alias("tie"))
            legs = legs.join(tied, [far, "w"], "left").where(F.col(count) - F.when((F.col(leaf) == F.col(other)) & F.col("tie").isNotNull(), 1).otherwise(0) > 0)
            ends.append(legs.select("l0", "l1", "l2", "l3", F.lit(role).alias("role"), F.col("w").alias("v")))
        return reduce(DataFrame.unionAll, ends).distinct()
    return None


def shape_supports(arcs: DataFrame, shape: str, p: Pattern, via: str = "fragments") -> DataFrame:
    """(shape, n_edges, l0..l3, support): one row for each labelled pattern of the shape; unused labels are null."""
    roles = (_roles_by_fragments(arcs, shape) if via == "fragments" else None)
    roles = _roles(_whole(arcs, shape), p.n) if roles is None else roles
    names = [f"l{i}" for i in range(p.n)]
    sizes = roles.groupBy(*names, "role").agg(F.count(F.lit(1)).alias("n")).groupBy(*names).agg(F.min("n").alias("support"))
    # label tuples that automorphisms map on each other are one pattern: the smallest tuple stands for it
    images = [F.struct(*[F.col(names[a[i]]).alias(names[i]) for i in range(p.n)]) for a in automorphisms(Pattern(p.n, p.edges))]
    smallest = F.array_min(F.array(*images))
    kept = sizes.where(F.struct(*[F.col(x) for x in names]) == smallest)
    return kept.select(F.lit(shape).alias("shape"), F.lit(p.m).alias("n_edges"), *[(F.col(f"l{i}") if i < p.n else F.lit(None)).cast("string").alias(f"l{i}") for i in range(4)], F.col("support").cast("long").alias("support"))


def cheaper_way(g: Graph) -> str:
    """Whole matchings where stars are fewer than label triples at their centres, else fragments."""
    by = g.arcs.groupBy("u", "lv").agg(F.count(F.lit(1)).alias("d")).groupBy("u").agg(F.sum("d").alias("d"), F.count(F.lit(1)).alias("k"))
    row = by.agg(F.sum(F.expr("CAST(d * (d - 1) * (d - 2) AS DOUBLE)")).alias("stars"), F.sum(F.expr("CAST(k * k * k + d * k * k * 3 AS DOUBLE)")).alias("triples")).first()
    return "embeddings" if (row["stars"] or 0) <= (row["triples"] or 0) else "fragments"


def _as_rows(g: Graph, found: dict, max_edges: int) -> DataFrame:
    """The rows of shape_supports() from tables of supports by labels, whose places are in the labels' order."""
    names, rows = found["labels"], []
    for m in range(1, max_edges + 1):
        for shape, p in SHAPES[m]:
            images = automorphisms(Pattern(p.n, p.edges))
            for at in zip(*found[shape].nonzero()):
                if all(at <= tuple(at[a[i]] for i in range(p.n)) for a in images):
                    rows.append((shape, p.m, *(names[i] for i in at), *[None] * (4 - p.n), int(found[shape][at])))
    return g.spark.createDataFrame(rows, "shape string, n_edges int, l0 string, l1 string, l2 string, l3 string, support long")


def supports(g: Graph, max_edges: int = 3, via: str = "auto", at_least: int | None = None) -> DataFrame:
    """Supports of all labelled patterns up to ``max_edges``; with ``at_least`` larger ones are grown from frequent edges alone (a part is never rarer than its whole)."""
    if via != "embeddings" and (found := labelled.supports(g, max_edges, at_least)) is not None:
        rows = _as_rows(g, found, max_edges)
        return rows if at_least is None else rows.where((F.col("n_edges") > 1) | (F.col("support") >= at_least))
    via = cheaper_way(g) if via == "auto" else via
    arcs = _arcs(g, None)
    out = [shape_supports(arcs, s, p, via) for s, p in SHAPES[1]]
    if at_least is not None:
        # a level is a job of its own: the next one starts from rows that are there
        out = [x.where(F.col("support") >= at_least).persist(StorageLevel.MEMORY_AND_DISK) for x in out]
        out[0].count()
        arcs = _arcs(g, out[0]).persist(StorageLevel.MEMORY_AND_DISK)
        arcs.count()
    for m in range(2, max_edges + 1):
        out += [shape_supports(arcs, s, p, via) for s, p in SHAPES[m]]
    return reduce(DataFrame.unionAll, out)


def fsm(g: Graph, threshold: int, max_edges: int = 3, via: str = "auto") -> DataFrame:
    """Labelled patterns whose smallest domain reaches the threshold."""
    return supports(g, max_edges, via, threshold).where(F.col("support") >= threshold)


def fsm_sweep(g: Graph, thresholds: list[int], max_edges: int = 3, via: str = "auto") -> DataFrame:
    """(threshold, shape, n): frequent patterns by shape for many thresholds from one pass over supports."""
    found = supports(g, max_edges, via, min(thresholds))
    marks = g.spark.createDataFrame([(int(t),) for t in thresholds], "threshold long")
    shapes = g.spark.createDataFrame([(s,) for m in range(1, max_edges + 1) for s, _ in SHAPES[m]], "shape string")
    hits = found.select("shape", F.explode(F.filter(F.array(*[F.lit(int(t)).cast("long") for t in thresholds]), lambda t: t <= F.col("support"))).alias("threshold")).groupBy("threshold", "shape").agg(F.count(F.lit(1)).alias("n"))
    return marks.join(F.broadcast(shapes)).join(hits, ["threshold", "shape"], "left").select("threshold", "shape", F.coalesce("n", F.lit(0)).cast("long").alias("n"))
