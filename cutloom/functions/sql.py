"""SQL surface: views of counts, and SQL functions for restrictions and codes."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType

from cutloom.operators.decompose import pattern_counts
from cutloom.operators.graph import Graph
from cutloom.patterns import catalogue
from cutloom.patterns.algebra import Pattern, automorphisms

NAMED = {"chain": catalogue.chain, "cycle": catalogue.cycle, "clique": catalogue.clique, "star": catalogue.star}


def register_sql(spark: SparkSession, g: Graph, wanted: list[tuple[str, int]], view: str = "pattern_counts") -> DataFrame:
    """A view (name, size, cnt) of edge-induced counts, functions choose2, choose3, ordered and geometric_mean, and the table function triangle_images.

    Queries on the view follow the usual path: parsed, analysed, optimised, run.
    """
    patterns = [NAMED[name](k) for name, k in wanted]
    counts = pattern_counts(g, patterns, names=[f"{a} {b}" for a, b in wanted])
    out = counts.select(F.split("pattern", " ")[0].alias("name"), F.split("pattern", " ")[1].cast("int").alias("size"), "cnt")
    out.createOrReplaceTempView(view)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION choose2(n BIGINT) RETURNS BIGINT RETURN n * (n - 1) div 2")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION choose3(n BIGINT) RETURNS BIGINT RETURN n * (n - 1) * (n - 2) div 6")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION ordered(a BIGINT, b BIGINT) RETURNS BOOLEAN RETURN a < b")
    spark.udf.register("geometric_mean", geometric_mean)
    spark.udtf.register("triangle_images", TriangleImages)
    return out


@pandas_udf(DoubleType())
def geometric_mean(values: pd.Series) -> float:
    """Geometric mean of positive values, as for speed-ups; null without any."""
    values = values[values > 0]
    return float(np.exp(np.log(values).mean())) if len(values) else None


def relabelled(rows: DataFrame, p: Pattern) -> DataFrame:
    """Each matching in all images under the pattern's automorphisms."""
    images = F.array(*[F.struct(*[F.col(f"m{a[i]}").alias(f"m{i}") for i in range(p.n)]) for a in automorphisms(p)])
    return rows.select(F.explode(images).alias("x")).select("x.*")


@udtf(returnType="m0: bigint, m1: bigint, m2: bigint")
class TriangleImages:
    """The six relabellings of a triangle, as a table function for SQL."""

    def eval(self, a: int, b: int, c: int):
        from itertools import permutations

        yield from permutations((a, b, c))
