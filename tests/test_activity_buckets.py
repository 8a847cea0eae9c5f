"""The interval join of event streams meets events by type and time bucket."""

from cutloom.operators.relational import QUERIES
from cutloom.streaming import activity


def test_pairs_are_joined_on_buckets_and_none_is_lost(spark):
    rows = [(u, t, k) for u in range(1, 5) for t in range(u, 400, 17 + u) for k in ("view", "buy")] + [(9, 0, "view"), (8, 60, "view"), (7, 120, "view"), (6, -1, "view")]
    events = spark.createDataFrame(rows, "user_id long, t long, event_type string").selectExpr("user_id", "timestamp_seconds(t) AS ts", "event_type")
    pairs = activity.activity_pairs(events, events)
    want = sorted((min(a, b), max(a, b), y) for a, x, k in rows for b, y, m in rows if k == m and a != b and x < y <= x + 60)
    assert sorted((r["src"], r["dst"], r["t"]) for r in pairs.selectExpr("src", "dst", "unix_seconds(ts) AS t").collect()) == want
    assert "bucket" in pairs._jdf.queryExecution().optimizedPlan().toString().split("Join Inner, ")[1].split("\n")[0]


def test_stream_equals_batch(spark):
    row = QUERIES["op_stream_batch_equal"](spark, "/root/testdata/sf0.001").first()
    assert (row["only_stream"], row["only_batch"]) == (0, 0) and row["edges"] > 0
