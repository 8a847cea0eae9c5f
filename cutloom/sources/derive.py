"""Graphs derived from the given tables."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutloom.operators.graph import Graph, normalize_edges


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Line filters of the part graphs.
PART_GRAPHS = {"bulk": "l_quantity >= 40", "bulk45": "l_quantity >= 45", "ret": "l_returnflag = 'R'", "all": "true"}
SUPPLIER_OFFSET = 1_000_000_000


def part_edges(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """Parts that share an order, both lines passing the filter of ``kind``."""
    lines = table(spark, sf_dir, "lineitem").where(PART_GRAPHS[kind]).select("l_orderkey", "l_partkey").distinct()
    a, b = lines.select("l_orderkey", F.col("l_partkey").alias("src")), lines.select("l_orderkey", F.col("l_partkey").alias("dst"))
    return a.join(b, "l_orderkey").where("src < dst").select("src", "dst").distinct()


def part_graph(spark: SparkSession, sf_dir: str, kind: str = "bulk", label: str | None = None) -> Graph:
    vertices = None if label is None else table(spark, sf_dir, "part").select(F.col("p_partkey").alias("v"), F.col(label).alias("label"))
    return Graph(part_edges(spark, sf_dir, kind), vertices)


def bipartite_graph(spark: SparkSession, sf_dir: str) -> Graph:
    lines = table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'")
    return Graph(lines.select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + SUPPLIER_OFFSET).alias("dst")).distinct())


def activity_edges(events: DataFrame, seconds: int = 60) -> DataFrame:
    """Distinct pairs of users with an event of one type at most so many seconds apart, not at the same instant.

    Time is cut into buckets of that length; an event meets its own bucket and
    the next, so the join is an equality join with a residual condition.
    """
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    span = seconds * 1_000_000
    a = events.select("event_type", F.col("user_id").alias("ua"), us.alias("ta"), F.explode(F.array(F.floor(us / span), F.floor(us / span) + 1)).alias("b"))
    b = events.select("event_type", F.col("user_id").alias("ub"), us.alias("tb"), F.floor(us / span).alias("b"))
    near = a.join(b, ["event_type", "b"]).where(f"ua <> ub AND tb > ta AND tb - ta <= {span}")
    return normalize_edges(near, "ua", "ub")


def activity_graph(spark: SparkSession, sf_dir: str) -> Graph:
    return Graph(activity_edges(table(spark, sf_dir, "events")))


#: Vectors of a block at most, and of a slice whose products with a block are held at once.
BLOCK, SLICE = 1 << 14, 256
#: So near to the bound a cosine is summed again one component after the other.
DOUBT = 1e-9


def _similar_pairs(least: float, blocks: int):
    """applyInArrow over (g, b, vec_id, embedding) of two blocks: (src, dst) of each similar pair across them, or within the one."""
    def run(rows: pa.Table) -> pa.Table:
        ids = rows.column("vec_id").to_numpy()
        column = rows.column("embedding").combine_chunks()
        sizes = np.diff(column.offsets.to_numpy())
        starts, flat = column.offsets.to_numpy()[:-1], column.values.to_numpy(zero_copy_only=False).astype(np.float64)
        block = rows.column("b").to_numpy()
        low, high = (block == x for x in divmod(rows.column("g")[0].as_py(), blocks))
        src, dst = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for size in np.unique(sizes):  # vectors of different lengths have no product
            mine, others = np.flatnonzero(low & (sizes == size)), np.flatnonzero(high & (sizes == size))
            at = np.arange(size)
            right = flat[starts[others][:, None] + at]
            right_norm = np.sqrt(np.cumsum(right * right, axis=1)[:, -1])
            for k in range(0, len(mine), SLICE):
                some = mine[k: k + SLICE]
                left = flat[starts[some][:, None] + at]
                norm = np.sqrt(np.cumsum(left * left, axis=1)[:, -1])
                with np.errstate(all="ignore"):
                    cosine = left @ right.T / (norm[:, None] * right_norm)
                    i, j = np.nonzero(~np.isfinite(cosine) | (np.abs(cosine - least) <= DOUBT))
                    for t in range(0, len(i), 1 << 16):
                        x, y = i[t: t + (1 << 16)], j[t: t + (1 << 16)]
                        cosine[x, y] = np.cumsum(left[x] * right[y], axis=1)[:, -1] / (norm[x] * right_norm[y])
                i, j = np.nonzero(~(cosine < least))  # NaN counts as larger than any number
                u, v = ids[some[i]], ids[others[j]]
                src.append(np.minimum(u, v)[u != v])
                dst.append(np.maximum(u, v)[u != v])
        src, dst = np.concatenate(src), np.concatenate(dst)
        order = np.lexsort((dst, src))
        src, dst = src[order], dst[order]
        new = np.ones(len(src), bool)
        new[1:] = (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])
        return pa.table({"src": src[new], "dst": dst[new]})

    return run


def similarity_edges(vectors: DataFrame, least: float = 0.3, blocks: int = 8) -> DataFrame:
    """Pairs of vectors by cosine, block by block: each pair of hash blocks meets in one group, which multiplies them slice by slice.

    A pair of ids is met in one group only.  Vectors that are null, hold null or
    have no length other than zero have no cosine.
    """
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    rows = rows.where("vec_id is not null and embedding is not null and not exists(embedding, x -> x is null) and exists(embedding, x -> x <> 0)")
    blocks = max(blocks, -(-rows.count() // BLOCK))
    rows = rows.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    sides = rows.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    sides = sides.select((F.least("b", "k") * blocks + F.greatest("b", "k")).alias("g"), "b", "vec_id", F.col("embedding").cast(vectors.schema["embedding"].dataType).alias("embedding"))
    return sides.groupBy("g").applyInArrow(_similar_pairs(least, blocks), "src long, dst long")


def similarity_graph(spark: SparkSession, sf_dir: str) -> Graph:
    vectors = table(spark, sf_dir, "embeddings")
    return Graph(similarity_edges(vectors), vectors.select(F.col("vec_id").alias("v"), F.col("label").cast("string").alias("label")))


def link_edges(pages: DataFrame) -> DataFrame:
    """(page_id, href) of each link of a page."""
    return pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href")).distinct()


def key_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """region-nation-customer and nation-supplier foreign keys; ids are the key times 8 plus the table's tag."""
    tagged = lambda c, tag: (F.col(c).cast("long") * 8 + tag).alias("x")
    nation = table(spark, sf_dir, "nation").select(tagged("n_regionkey", 0).alias("a"), tagged("n_nationkey", 1).alias("b"))
    customer = table(spark, sf_dir, "customer").select(tagged("c_nationkey", 1).alias("a"), tagged("c_custkey", 2).alias("b"))
    supplier = table(spark, sf_dir, "supplier").select(tagged("s_nationkey", 1).alias("a"), tagged("s_suppkey", 3).alias("b"))
    return normalize_edges(nation.unionAll(customer).unionAll(supplier), "a", "b")


def rmat_edges(spark: SparkSession, scale: int, factor: int, seed: int = 1, odds: tuple[float, float, float, float] = (0.57, 0.19, 0.19, 0.05)) -> DataFrame:
    """A recursive-matrix graph of 2^scale vertices and about factor * 2^scale edges; each level picks a quadrant by hash."""
    a, b, c, _ = odds
    rows = spark.range(factor << scale)
    src = dst = F.lit(0).cast("long")
    for level in range(scale):
        r = F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit(level), "id"), 11) / F.lit(float(1 << 53))
        src = src * 2 + (r >= a + b).cast("long")
        dst = dst * 2 + (((r >= a) & (r < a + b)) | (r >= a + b + c)).cast("long")
    return normalize_edges(rows.select(src.alias("src"), dst.alias("dst")))


def synthetic_labels(g: Graph, kinds: int, seed: int = 1) -> Graph:
    """The graph with hashed labels, as for unlabelled inputs that are mined."""
    v = g.degrees().select("v", F.pmod(F.xxhash64("v", F.lit(seed)), F.lit(kinds)).cast("string").alias("label"))
    return Graph(g.edges, v, persist=False)
