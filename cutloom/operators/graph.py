"""Graphs as DataFrames: canonical edges, arcs, adjacency, labels."""

from __future__ import annotations

import tempfile
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

from cutloom.operators import kernel, pieces
from cutloom.plans.cost import CostModel, UniformModel


def normalize_edges(pairs: DataFrame, a: str = "src", b: str = "dst") -> DataFrame:
    """edges(src, dst), src < dst: loops and null ends dropped, directions folded, duplicates removed."""
    x, y = F.col(a).cast("long"), F.col(b).cast("long")
    return pairs.select(F.least(x, y).alias("src"), F.greatest(x, y).alias("dst")).where("src < dst").distinct()


def shared_folder(spark) -> str:
    """The folder that the driver and all executors share: spark.checkpoint.dir, or the context's own.

    Only a session on one machine (as in tests) gets a folder of its own where
    none is set; on a cluster that is an error.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="cutloom-checkpoint-"))
        folder = spark.sparkContext.getCheckpointDir()
    return folder


def reliable(df: DataFrame) -> DataFrame:
    """Cut the lineage in the shared checkpoint folder of the session."""
    context = df.sparkSession.sparkContext
    if not context.getCheckpointDir():
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


class Graph:
    """An undirected simple graph: ``edges(src, dst)`` with src < dst, and ``vertices(v, label)`` if it is labelled.

    Edges are persisted, spilling to disk, since every level of every plan
    joins them.  They are counted at once: then the planner knows their size
    and broadcasts them where that is below the session's threshold, and
    shuffles them beyond it.
    """

    def __init__(self, edges: DataFrame, vertices: DataFrame | None = None, persist: bool = True):
        self.edges = edges.persist(StorageLevel.MEMORY_AND_DISK) if persist else edges
        self.vertices = vertices
        self.size = self.edges.count() if persist else None
        self.profile: CostModel | None = None
        self._lists = self._degrees = None

    @property
    def spark(self):
        return self.edges.sparkSession

    @cached_property
    def arcs(self) -> DataFrame:
        """Both directions (u, v); labelled graphs add lu and lv."""
        both = self.edges.select(F.col("src").alias("u"), F.col("dst").alias("v")).unionAll(self.edges.select(F.col("dst").alias("u"), F.col("src").alias("v")))
        if self.vertices is None:
            return both
        label = self.vertices.select(F.col("v").alias("__v"), "label")
        both = both.join(label, F.col("u") == F.col("__v"), "left").drop("__v").withColumnRenamed("label", "lu")
        return both.join(label, F.col("v") == F.col("__v"), "left").drop("__v").withColumnRenamed("label", "lv").persist(StorageLevel.MEMORY_AND_DISK)

    @property
    def pairs(self) -> DataFrame:
        """Both directions without labels."""
        return self.edges.select(F.col("src").alias("u"), F.col("dst").alias("v")).unionAll(self.edges.select(F.col("dst").alias("u"), F.col("src").alias("v")))

    def degrees(self) -> DataFrame:
        """(v, deg); made once and kept where the graph is large."""
        if self.size is not None and not self.fits():
            if self._degrees is None:
                self._degrees = pieces.degrees(self.edges).persist(StorageLevel.MEMORY_AND_DISK)
            return self._degrees
        return self.pairs.groupBy(F.col("u").alias("v")).agg(F.count(F.lit(1)).alias("deg"))

    def adjacency(self, block: int | None = None) -> DataFrame:
        """(v, deg, nbrs sorted); with ``block`` a vertex's neighbours come in rows of at most that many (v, part, ...)."""
        if block is None:
            return self.pairs.groupBy(F.col("u").alias("v")).agg(F.count(F.lit(1)).cast("int").alias("deg"), F.array_sort(F.collect_list("v")).alias("nbrs"))
        parts = self.pairs.join(self.degrees().select(F.col("v").alias("u"), "deg"), "u")
        part = F.pmod(F.xxhash64("v"), F.ceil(F.col("deg") / block)).cast("int")
        return parts.groupBy(F.col("u").alias("v"), part.alias("part")).agg(F.count(F.lit(1)).cast("int").alias("deg"), F.array_sort(F.collect_list("v")).alias("nbrs"))

    def fits(self) -> bool:
        """Whether the neighbour lists are few enough to be sent to every task."""
        return self.size is not None and 2 * self.size <= kernel.MOST_ARCS

    def lists(self):
        """The neighbour lists of a graph that fits, as a broadcast; made once."""
        if self._lists is None:
            bounds = self.edges.agg(F.min(F.least("src", "dst")).alias("low"), F.max(F.greatest("src", "dst")).alias("high")).first()
            kind = "int" if bounds["low"] is None or -(1 << 31) <= bounds["low"] <= bounds["high"] < 1 << 31 else "long"
            ends = self.edges.select(F.col("src").cast(kind).alias("src"), F.col("dst").cast(kind).alias("dst")).toArrow()  # half the driver's memory, where ids are small
            src, dst = ends.column("src").to_numpy(), ends.column("dst").to_numpy()
            del ends
            pa.default_memory_pool().release_unused()
            found = kernel.Lists.of(src, dst)
            del src, dst
            self.largest_degree = int(np.diff(found.at).max(initial=0))
            self._lists = self.spark.sparkContext.broadcast((found.ids, found.at, found.near, found.left, found.bits))
            self._two_sided = found.left is not None
        return self._lists

    def two_sided(self) -> bool:
        """Whether the neighbour lists show that no vertex is a source and a target, so that no odd cycle exists; False where they aren't made."""
        return self.fits() and self.size > 0 and (self.lists() and self._two_sided)

    def with_degree_order(self) -> DataFrame:
        """arcs (u, v) from the end that is smaller by (degree, id): out-degrees are at most the root of twice the edges."""
        d = self.degrees()
        e = self.edges.join(d.select(F.col("v").alias("src"), F.col("deg").alias("ds")), "src").join(d.select(F.col("v").alias("dst"), F.col("deg").alias("dd")), "dst")
        first = F.struct("ds", "src") < F.struct(F.col("dd").alias("ds"), F.col("dst").alias("src"))
        return e.select(F.when(first, F.col("src")).otherwise(F.col("dst")).alias("u"), F.when(first, F.col("dst")).otherwise(F.col("src")).alias("v"))

    def model(self) -> CostModel:
        """What plans are priced with: the graph's profile once one was taken (see operators/profile.py), else its size and density."""
        if self.profile is None:
            n, m = self.stats()
            self.profile = UniformModel(max(n, 2), max(2 * m / max(n, 1), 1e-9))
        return self.profile

    def release(self) -> None:
        """Drop what is persisted."""
        self.edges.unpersist()
        if self._degrees is not None:
            self._degrees.unpersist()
        if "arcs" in self.__dict__:
            self.arcs.unpersist()

    def stats(self) -> tuple[int, int]:
        """Vertices with an edge, and edges."""
        row = self.degrees().agg(F.count(F.lit(1)).alias("n"), F.sum("deg").alias("d")).first()
        return row["n"], (row["d"] or 0) // 2


def degree_stats(g: Graph) -> DataFrame:
    return g.degrees().agg(F.count(F.lit(1)).alias("n"), F.max("deg").alias("max_deg"), F.sum("deg").alias("sum_deg"), F.expr("percentile(deg, 0.5)").alias("median_deg"))
