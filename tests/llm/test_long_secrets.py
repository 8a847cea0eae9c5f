"""Secrets in long rows: time little more than in proportion, results as those of the pieces."""

import random
import string
import time

import pytest
from pyspark.sql import functions as F

pytest.importorskip("cutloom.llm")
from cutloom.llm import secrets  # noqa: E402


def _seconds(df):
    began = time.perf_counter()
    rows = df.collect()
    return time.perf_counter() - began, rows


def test_a_candidate_of_a_million_characters(spark):
    rng = random.Random(1)
    noise = "".join(rng.choices(string.ascii_letters + string.digits + "+/", k=1_000_000))
    texts = [("data:" + noise[: 1000] + " end",), ("data:" + noise + " end",)]
    took, rows = _seconds(secrets.scanned(spark.createDataFrame(texts, "text string")).select("text", F.expr("element_at(__spans.all, 1)").alias("s"), F.size("__spans.all").alias("n")))
    for r in rows:
        assert r["n"] == 1 and (r["s"]["start"], r["s"]["end"]) == (5, len(r["text"]) - 4)
    assert took < 120


def test_fifty_thousand_matches(spark):
    one = "token=abcdefg1 and 0123456789abcdef0123456789 or Q7xK2mV9pL4nR8tW1zYc5Ha3, "
    texts = [(one * 20_000,)]
    took, rows = _seconds(secrets.scanned(spark.createDataFrame(texts, "text string")).select(F.expr("transform(__spans.all, s -> concat_ws(':', s.start, s.end, s.kind))").alias("s")))
    first = secrets.scanned(spark.createDataFrame([(one,)], "text string")).first()["__spans"]["all"]
    assert len(first) == 3
    assert rows[0]["s"] == [f"{s['start'] + k * len(one)}:{s['end'] + k * len(one)}:{s['kind']}" for k in range(20_000) for s in first]
    assert took < 120
    text = secrets.redacted(spark.createDataFrame([(one * 20_000, 0)], "text string, n_chars int")).first()
    assert text["text"] == "[assign] and [hex] or [entropy], " * 20_000 and text["n_chars"] == len(text["text"])


def test_running_over_many_chunks(spark):
    values = [random.Random(3).randrange(100) for _ in range(1000)]
    for n in (0, 1, 127, 128, 129, 1000):
        df = spark.createDataFrame([(values[:n],)], "v array<long>")
        sums, most = df.select(secrets.running(F.col("v"), lambda a, x: a + x), secrets.running(F.col("v"), lambda a, x: F.greatest(a, x))).first()
        assert sums == [sum(values[:i]) for i in range(n)] and most == [max(values[:i], default=0) for i in range(n)]


def test_clashing_columns(spark):
    df = spark.createDataFrame([("token=abcdefg1", "a", "b", 3), (None, "a", "b", 3)], "text string, __spans string, clean string, n_chars int")
    out = secrets.redacted(df)
    assert out.columns == df.columns
    assert sorted(map(tuple, out.collect()), key=str) == [("[assign]", "a", "b", 8), (None, "a", "b", 3)]
