"""Edge lists in files, and sinks for results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutloom.operators.graph import normalize_edges


def read_edges(spark: SparkSession, path: str, fmt: str = "text", sep: str = r"[\s,]+", comment: str = "#") -> DataFrame:
    """edges(src, dst) from text, csv, json or parquet with explicit types; comment lines and loops go."""
    if fmt == "text":
        lines = spark.read.text(path).where(~F.col("value").startswith(comment) & (F.trim("value") != ""))
        cut = F.split(F.trim("value"), sep)
        return normalize_edges(lines.select(F.try_element_at(cut, F.lit(1)).cast("long").alias("src"), F.try_element_at(cut, F.lit(2)).cast("long").alias("dst")))
    schema = "src long, dst long"
    if fmt == "csv":
        return normalize_edges(spark.read.csv(path, schema=schema, comment=comment, sep="," if sep == r"[\s,]+" else sep))
    if fmt == "json":
        return normalize_edges(spark.read.json(path, schema=schema))
    return normalize_edges(spark.read.parquet(path).select("src", "dst"))


def write_counts(counts: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Pattern counts, Parquet partitioned by pattern size, else json or csv."""
    out = counts.write.mode("overwrite")
    if fmt == "parquet":
        out.partitionBy("n").parquet(path)
    elif fmt == "json":
        out.json(path)
    else:
        out.option("header", True).csv(path)


def write_bucketed(arcs: DataFrame, name: str, buckets: int) -> None:
    """arcs(u, v) as a table bucketed and sorted by u: later arc joins on u need no exchange."""
    arcs.write.mode("overwrite").bucketBy(buckets, "u").sortBy("u", "v").saveAsTable(name)


def discard(df: DataFrame) -> None:
    """Run a plan for its time."""
    df.write.format("noop").mode("overwrite").save()
