"""Sources, sinks, the SQL surface and streams."""

import pytest
from pyspark.sql import functions as F

from conftest import SF
from cutloom.functions.sql import register_sql, relabelled
from cutloom.operators.decompose import pattern_count
from cutloom.operators.graph import Graph
from cutloom.patterns import clique, cycle
from cutloom.sources import derive, files
from cutloom.streaming import activity


@pytest.mark.parametrize(("kind", "n", "m", "triangles"), [("bulk", 190, 589, 226), ("bulk45", 148, 172, 26), ("ret", 200, 1220, 830)])
def test_part_graphs(spark, kind, n, m, triangles):
    g = derive.part_graph(spark, SF, kind)
    assert g.stats() == (n, m) and pattern_count(g, clique(3)) == triangles


def test_bipartite_and_similarity(spark):
    g = derive.bipartite_graph(spark, SF)
    assert g.size == 1251 and pattern_count(g, clique(3)) == 0
    assert derive.similarity_graph(spark, SF).size == 920


def test_flagship(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).first()["cnt"] == 353


def test_text_edges(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# comment\n1 2\n2\t1\n3 3\n2,5\n\n")
    assert sorted(map(tuple, files.read_edges(spark, str(tmp_path / "e.txt")).collect())) == [(1, 2), (2, 5)]


def test_counts_are_written(spark, tmp_path):
    rows = spark.createDataFrame([("01", 2, 1, 5)], "pattern string, n int, m int, cnt long")
    for fmt in ("parquet", "json", "csv"):
        files.write_counts(rows, str(tmp_path / fmt), fmt)
    assert spark.read.parquet(str(tmp_path / "parquet")).count() == 1


def test_sql_surface(spark):
    g = derive.part_graph(spark, SF, "bulk45")
    register_sql(spark, g, [("chain", 3), ("clique", 3), ("cycle", 4)])
    got = {(r["name"], r["size"]): r["cnt"] for r in spark.sql("SELECT * FROM pattern_counts").collect()}
    assert got == {("chain", 3): 361, ("clique", 3): 26, ("cycle", 4): 6}
    assert spark.sql("SELECT choose2(5) AS a, choose3(5) AS b").first() == (10, 10)


def test_relabelled(spark):
    one = spark.createDataFrame([(1, 2, 3)], "m0 long, m1 long, m2 long")
    assert relabelled(one, clique(3)).distinct().count() == 6


def test_rmat_is_repeatable(spark):
    a, b = derive.rmat_edges(spark, 7, 4, 5), derive.rmat_edges(spark, 7, 4, 5)
    assert a.exceptAll(b).count() == 0 and 300 < a.count() <= 512


def test_stream_edges_equal_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    left = activity.events_stream(spark, str(tmp_path / "in"), "365 days")
    right = activity.events_stream(spark, str(tmp_path / "in"), "365 days")
    q = activity.activity_pairs(left, right).writeStream.format("memory").queryName("pairs").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    q.awaitTermination(240)
    got = set(map(tuple, spark.table("pairs").select("src", "dst").distinct().collect()))
    assert got == set(map(tuple, derive.activity_edges(events).collect()))


def test_stream_counts_equal_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet")
    stream = spark.readStream.schema(events.schema).parquet(f"{SF}/events.parque[t]")
    q = activity.tumbling_counts(stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")).writeStream.outputMode("complete").format("memory").queryName("tumbling").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination(240)
    got = {(r["start"], r["event_type"]): r["n"] for r in spark.table("tumbling").collect()}
    want = {(r["start"], r["event_type"]): r["n"] for r in activity.tumbling_counts(events.withColumn("ts", F.col("ts").cast("timestamp"))).collect()}
    assert got == want


def test_closed_cycle_stays_small(spark):
    g = Graph(spark.createDataFrame([(1, 2), (2, 3), (3, 4), (1, 4)], "src long, dst long"))
    assert pattern_count(g, cycle(4)) == 1 and g.degrees().where(F.col("deg") != 2).count() == 0
