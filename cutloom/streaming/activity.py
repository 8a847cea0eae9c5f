"""Structured Streaming over events."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def events_stream(spark: SparkSession, path: str, lateness: str = "10 minutes", per_batch: int = 1) -> DataFrame:
    schema = spark.read.parquet(path).schema
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", per_batch).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)


def tumbling_counts(events: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


def activity_pairs(left: DataFrame, right: DataFrame, seconds: int = 60) -> DataFrame:
    """Stream-stream interval join: (src, dst, ts) of users with events of one type at most so many seconds apart.

    Time is cut into buckets of that length, and an event meets its own bucket
    and the next alone, so state is looked up by type and bucket.
    """
    bucket = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / (seconds * 1_000_000))
    a = left.select("event_type", F.col("user_id").alias("ua"), F.col("ts").alias("ta"), F.explode(F.array(bucket, bucket + 1)).alias("slot"))
    b = right.select(F.col("event_type").alias("kind"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"), bucket.alias("bucket"))
    near = a.join(b, (F.col("event_type") == F.col("kind")) & (F.col("slot") == F.col("bucket")) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr(f"interval {seconds} seconds")) & (F.col("ua") != F.col("ub")))
    return near.select(F.least("ua", "ub").alias("src"), F.greatest("ua", "ub").alias("dst"), F.col("tb").alias("ts"))


def first_seen(pairs: DataFrame) -> DataFrame:
    """Each edge once while its watermark holds it."""
    return pairs.dropDuplicatesWithinWatermark(["src", "dst"])


def running_degrees(pairs: DataFrame) -> DataFrame:
    """(v, deg, wedges) after each batch that touches v: degree and the pairs of its neighbours, kept as state."""
    ends = pairs.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("u")), F.struct(F.col("dst").alias("v"), F.col("src").alias("u")))).alias("x")).select("x.v", "x.u")

    def step(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        near = set(state.get[0]) if state.exists else set()
        for f in frames:
            near |= set(f["u"].tolist())
        state.update((sorted(near),))
        d = len(near)
        yield pd.DataFrame({"v": [key[0]], "deg": [d], "wedges": [d * (d - 1) // 2]})

    return ends.groupBy("v").applyInPandasWithState(step, "v long, deg long, wedges long", "near array<long>", "update", "NoTimeout")


def each_batch(stream: DataFrame, fn: Callable[[DataFrame, int], None], checkpoint: str):
    """Recount with batch code on what a batch changed."""
    return stream.writeStream.foreachBatch(fn).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
