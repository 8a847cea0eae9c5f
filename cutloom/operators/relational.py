"""Small typed uses of the relational operators that the engine stands on, over the given tables."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cutloom.operators.enumerate import enumerate_matchings
from cutloom.operators.graph import Graph, degree_stats, normalize_edges
from cutloom.patterns.algebra import Pattern, restrictions
from cutloom.patterns.catalogue import clique
from cutloom.sources.derive import activity_edges, bipartite_graph, key_edges, link_edges, part_edges, part_graph, similarity_edges, table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def op(fn):
    QUERIES[fn.__name__] = fn
    return fn


def _bulk(spark: SparkSession, sf_dir: str, label: str | None = None) -> Graph:
    return part_graph(spark, sf_dir, "bulk", label)


def _n(x="*") -> F.Column:
    return F.count(F.lit(1)).alias("n") if x == "*" else F.count(x).alias("n")


@op
def op_corr(spark, sf_dir):
    """Correlation of a part's degrees in two graphs, in millionths (from exact sums, so it is the same in any order)."""
    a, b = _bulk(spark, sf_dir).degrees(), part_graph(spark, sf_dir, "ret").degrees().select("v", F.col("deg").alias("other"))
    both = a.join(b, "v").agg(F.corr("deg", "other").alias("r"), F.regr_slope("other", "deg").alias("slope"), _n())
    return both.select(F.round(F.col("r") * 1e6).cast("long").alias("r"), F.round(F.col("slope") * 1e6).cast("long").alias("slope"), "n")


@op
def op_stream_batch_equal(spark, sf_dir):
    """Edges of the interval join of two event streams, run to the end, against the batch join: how many of either kind the other lacks."""
    from cutloom.streaming import activity

    folder = f"{_shared(spark)}/stream-{uuid.uuid4().hex}"
    events = table(spark, sf_dir, "events")
    events.repartition(4).write.parquet(f"{folder}/in")
    left, right = (activity.events_stream(spark, f"{folder}/in", "3650 days", 4) for _ in range(2))
    stream = activity.activity_pairs(left, right).writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    stream.awaitTermination()
    streamed, batch = spark.read.parquet(f"{folder}/out").select("src", "dst").distinct(), activity_edges(events)
    count = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    return count(batch, "edges").join(F.broadcast(count(streamed.exceptAll(batch), "only_stream"))).join(F.broadcast(count(batch.exceptAll(streamed), "only_batch")))


def _shared(spark) -> str:
    from cutloom.operators.graph import shared_folder

    return shared_folder(spark)


@op
def op_scan_edges(spark, sf_dir):
    return part_edges(spark, sf_dir, "bulk")


@op
def op_normalize(spark, sf_dir):
    e = part_edges(spark, sf_dir, "bulk")
    dirty = e.unionAll(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).unionAll(e.select("src", F.col("src").alias("dst")))
    return normalize_edges(dirty)


@op
def op_degree_stats(spark, sf_dir):
    return degree_stats(_bulk(spark, sf_dir)).select("n", "max_deg", "sum_deg", "median_deg")


@op
def op_degree_histogram(spark, sf_dir):
    return _bulk(spark, sf_dir).degrees().groupBy("deg").agg(_n())


@op
def op_filter_label(spark, sf_dir):
    return table(spark, sf_dir, "part").where(F.col("p_type").isin("PROMO", "SMALL") & F.col("p_size").between(10, 20)).select("p_partkey", "p_type", "p_size")


@op
def op_project_expr(spark, sf_dir):
    size = F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "middle").otherwise("large")
    return table(spark, sf_dir, "part").select("p_partkey", F.concat_ws("/", F.lower("p_type"), F.substring("p_brand", -2, 2)).alias("code"), size.alias("size_class"))


@op
def op_broadcast_join(spark, sf_dir):
    """Edges by label pair; the label side is broadcast where the planner knows it is small."""
    return _bulk(spark, sf_dir, "p_type").arcs.groupBy("lu", "lv").agg(_n())


@op
def op_merge_join(spark, sf_dir):
    a = _bulk(spark, sf_dir).pairs
    wedge = a.hint("merge").join(a.select(F.col("u").alias("w"), F.col("v").alias("x")), F.col("v") == F.col("w")).where("u < x")
    return wedge.groupBy("u", "x").agg(_n())


@op
def op_semi_join(spark, sf_dir):
    return enumerate_matchings(_bulk(spark, sf_dir), clique(3), pinned=restrictions(clique(3))).agg(_n())


@op
def op_anti_join(spark, sf_dir):
    p = Pattern.parse("01 02")
    return enumerate_matchings(_bulk(spark, sf_dir), p, induced="vertex", pinned=restrictions(p)).agg(_n())


@op
def op_outer_join(spark, sf_dir):
    parts = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("v"))
    return parts.join(_bulk(spark, sf_dir).degrees(), "v", "left").select("v", F.coalesce("deg", F.lit(0)).alias("deg"))


@op
def op_cross_guard(spark, sf_dir):
    """A grid of labels: both sides are distinct labels, so the product is bounded by their number squared."""
    kinds = table(spark, sf_dir, "part").select("p_type").distinct()
    return kinds.crossJoin(kinds.withColumnRenamed("p_type", "other"))


@op
def op_range_join(spark, sf_dir):
    return activity_edges(table(spark, sf_dir, "events"))


@op
def op_asof_join(spark, sf_dir):
    """Each event with the latest earlier one of its type."""
    w = Window.partitionBy("event_type").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, sf_dir, "events").select("event_id", F.last("event_id", ignorenulls=True).over(w).alias("before"))


@op
def op_lateral_topk(spark, sf_dir):
    rank = F.row_number().over(Window.partitionBy("u").orderBy("v"))
    return _bulk(spark, sf_dir).pairs.withColumn("k", rank).where("k <= 3").select("u", "v", "k")


@op
def op_group_label_pairs(spark, sf_dir):
    a = _bulk(spark, sf_dir, "p_brand").arcs.where("u < v")
    return a.groupBy(F.least("lu", "lv").alias("a"), F.greatest("lu", "lv").alias("b")).agg(_n())


@op
def op_distinct_agg(spark, sf_dir):
    """Domain sizes: vertices of each label with a neighbour of each label."""
    return _bulk(spark, sf_dir, "p_type").arcs.groupBy("lu", "lv").agg(F.countDistinct("u").alias("n"))


@op
def op_approx_distinct(spark, sf_dir):
    return _bulk(spark, sf_dir).pairs.agg(F.approx_count_distinct("u", 0.02).alias("approx"), F.countDistinct("u").alias("exact"))


def _labelled_parts(spark, sf_dir):
    return _bulk(spark, sf_dir).degrees().join(table(spark, sf_dir, "part").select(F.col("p_partkey").alias("v"), "p_type", "p_brand"), "v")


@op
def op_rollup(spark, sf_dir):
    return _labelled_parts(spark, sf_dir).rollup("p_type", "p_brand").agg(F.sum("deg").alias("arcs"), F.grouping_id().alias("gid"))


@op
def op_cube(spark, sf_dir):
    return _labelled_parts(spark, sf_dir).cube("p_type", "p_brand").agg(F.sum("deg").alias("arcs"), F.grouping_id().alias("gid"))


@op
def op_grouping_sets(spark, sf_dir):
    return _labelled_parts(spark, sf_dir).groupingSets([["p_type"], ["p_brand"]], "p_type", "p_brand").agg(F.sum("deg").alias("arcs"))


@op
def op_pivot_labels(spark, sf_dir):
    kinds = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
    return _bulk(spark, sf_dir, "p_type").arcs.groupBy("lu").pivot("lv", kinds).agg(F.count(F.lit(1))).na.fill(0)


@op
def op_unpivot_roles(spark, sf_dir):
    rows = enumerate_matchings(_bulk(spark, sf_dir), clique(3), pinned=restrictions(clique(3)))
    return rows.unpivot([], ["m0", "m1", "m2"], "role", "v").groupBy("role").agg(_n(), F.sum("v").alias("sum_v"))


@op
def op_rank_degree(spark, sf_dir):
    w, tie = Window.partitionBy("p_type").orderBy(F.desc("deg")), Window.partitionBy("p_type").orderBy(F.desc("deg"), "v")
    return _labelled_parts(spark, sf_dir).select("v", F.row_number().over(tie).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(tie).alias("nt"))


@op
def op_lead_lag(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    return table(spark, sf_dir, "events").select("event_id", (F.lead(us).over(w) - us).alias("gap_us"), F.lag("event_id").over(w).alias("previous"))


@op
def op_running_edges(spark, sf_dir):
    days = table(spark, sf_dir, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(_n())
    return days.select("month", F.sum("n").over(Window.orderBy("month").rowsBetween(Window.unboundedPreceding, 0)).alias("total"))


@op
def op_range_frame(spark, sf_dir):
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy(us).rangeBetween(-3_600_000_000, 0)
    return table(spark, sf_dir, "events").select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@op
def op_topk_hubs(spark, sf_dir):
    return _bulk(spark, sf_dir).degrees().orderBy(F.desc("deg"), "v").limit(10)


@op
def op_union(spark, sf_dir):
    return part_edges(spark, sf_dir, "bulk").unionByName(part_edges(spark, sf_dir, "ret")).distinct()


@op
def op_intersect(spark, sf_dir):
    return part_edges(spark, sf_dir, "bulk").intersect(part_edges(spark, sf_dir, "ret"))


@op
def op_except(spark, sf_dir):
    return part_edges(spark, sf_dir, "bulk").exceptAll(part_edges(spark, sf_dir, "ret"))


@op
def op_string_fn(spark, sf_dir):
    p = table(spark, sf_dir, "part")
    return p.select("p_partkey", F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("padded"), F.upper(F.substring("p_type", 1, 3)).alias("short"), F.length("p_brand").alias("len"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"))


@op
def op_date_fn(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.date_format("ts", "yyyy-MM-dd HH").alias("hour")).agg(_n())


@op
def op_math_fn(spark, sf_dir):
    return _bulk(spark, sf_dir).degrees().select("v", F.expr("deg * (deg - 1) div 2").alias("choose2"), F.greatest("deg", F.lit(3)).alias("at_least"), F.pmod(F.col("v"), F.lit(7)).alias("r"))


@op
def op_array_intersect(spark, sf_dir):
    """Common neighbours of each edge by neighbour sets."""
    g = _bulk(spark, sf_dir)
    adj = g.adjacency()
    return g.edges.join(adj.select(F.col("v").alias("src"), F.col("nbrs").alias("a")), "src").join(adj.select(F.col("v").alias("dst"), F.col("nbrs").alias("b")), "dst").select("src", "dst", F.size(F.array_intersect("a", "b")).alias("n"))


@op
def op_array_except_trim(spark, sf_dir):
    """For each edge, the neighbours of src that dst lacks and that exceed dst."""
    g = _bulk(spark, sf_dir)
    adj = g.adjacency()
    rows = g.edges.join(adj.select(F.col("v").alias("src"), F.col("nbrs").alias("a")), "src").join(adj.select(F.col("v").alias("dst"), F.col("nbrs").alias("b")), "dst")
    return rows.select("src", "dst", F.size(F.filter(F.array_except("a", "b"), lambda x: x > F.col("dst"))).alias("n"))


@op
def op_map_roles(spark, sf_dir):
    rows = enumerate_matchings(_bulk(spark, sf_dir), clique(3), pinned=restrictions(clique(3)))
    m = F.map_from_arrays(F.array(*map(F.lit, ("a", "b", "c"))), F.array("m0", "m1", "m2"))
    return rows.select(m.alias("m")).select(F.col("m")["a"].alias("a"), F.col("m")["b"].alias("b"), F.size(F.map_keys("m")).alias("k"))


@op
def op_json_props(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))


@op
def op_page_links(spark, sf_dir):
    return link_edges(table(spark, sf_dir, "pages"))


@op
def op_sim_edges(spark, sf_dir):
    return similarity_edges(table(spark, sf_dir, "embeddings"))


@op
def op_conversation_chain(spark, sf_dir):
    """Arcs between consecutive turns, counted by the roles at their ends."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    rows = table(spark, sf_dir, "conversations").select(F.col("role").alias("a"), F.lead("role").over(w).alias("b"))
    return rows.where("b IS NOT NULL").groupBy("a", "b").agg(_n())


@op
def op_fk_graph(spark, sf_dir):
    return key_edges(spark, sf_dir)


@op
def op_doc_label_graph(spark, sf_dir):
    """Documents tied to their source, counted by the quality label."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "source")
    return docs.join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id").groupBy("source", "quality").agg(_n())


@op
def op_udtf_automorphisms(spark, sf_dir):
    from cutloom.functions.sql import relabelled

    rows = enumerate_matchings(_bulk(spark, sf_dir), clique(3), pinned=restrictions(clique(3)))
    return relabelled(rows, clique(3))


@op
def op_bip_degrees(spark, sf_dir):
    return bipartite_graph(spark, sf_dir).degrees()


_BULK = "WITH l AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS k FROM lineitem WHERE l_quantity >= 40), e AS (SELECT DISTINCT x.k AS src, y.k AS dst FROM l x JOIN l y ON x.o = y.o AND x.k < y.k), a AS (SELECT src AS u, dst AS v FROM e UNION ALL SELECT dst, src FROM e), d AS (SELECT u AS v, count(*)::BIGINT AS deg FROM a GROUP BY u)"
_RET = ", lr AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS k FROM lineitem WHERE l_returnflag = 'R'), er AS (SELECT DISTINCT x.k AS src, y.k AS dst FROM lr x JOIN lr y ON x.o = y.o AND x.k < y.k)"
_TRI = ", t AS (SELECT x.src AS m0, x.dst AS m1, y.dst AS m2 FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst)"
_LAB = ", ld AS (SELECT d.v, deg, p_type, p_brand FROM d JOIN part ON p_partkey = d.v), la AS (SELECT u, v, x.p_type AS lu, y.p_type AS lv, x.p_brand AS bu, y.p_brand AS bv FROM a JOIN part x ON x.p_partkey = u JOIN part y ON y.p_partkey = v)"

ORACLES = {
    "op_scan_edges": f"{_BULK} SELECT src, dst FROM e", "op_normalize": f"{_BULK} SELECT src, dst FROM e",
    "op_degree_stats": f"{_BULK} SELECT count(*)::BIGINT AS n, max(deg)::BIGINT AS max_deg, sum(deg)::BIGINT AS sum_deg, quantile_cont(deg, 0.5)::DOUBLE AS median_deg FROM d",
    "op_degree_histogram": f"{_BULK} SELECT deg, count(*)::BIGINT AS n FROM d GROUP BY deg",
    "op_filter_label": "SELECT p_partkey, p_type, p_size FROM part WHERE p_type IN ('PROMO', 'SMALL') AND p_size BETWEEN 10 AND 20",
    "op_project_expr": "SELECT p_partkey, lower(p_type) || '/' || right(p_brand, 2) AS code, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'middle' ELSE 'large' END AS size_class FROM part",
    "op_broadcast_join": f"{_BULK}{_LAB} SELECT lu, lv, count(*)::BIGINT AS n FROM la GROUP BY lu, lv",
    "op_merge_join": f"{_BULK} SELECT x.u, y.v AS x, count(*)::BIGINT AS n FROM a x JOIN a y ON x.v = y.u WHERE x.u < y.v GROUP BY ALL",
    "op_semi_join": f"{_BULK}{_TRI} SELECT count(*)::BIGINT AS n FROM t",
    "op_anti_join": f"{_BULK} SELECT count(*)::BIGINT AS n FROM a x JOIN a y ON x.v = y.u AND x.u < y.v WHERE NOT EXISTS (SELECT 1 FROM e WHERE src = x.u AND dst = y.v)",
    "op_outer_join": f"{_BULK} SELECT p_partkey AS v, coalesce(deg, 0)::BIGINT AS deg FROM part LEFT JOIN d ON d.v = p_partkey",
    "op_cross_guard": "SELECT x.p_type, y.p_type AS other FROM (SELECT DISTINCT p_type FROM part) x, (SELECT DISTINCT p_type FROM part) y",
    "op_range_join": "SELECT DISTINCT least(x.user_id, y.user_id) AS src, greatest(x.user_id, y.user_id) AS dst FROM events x JOIN events y ON x.event_type = y.event_type AND x.user_id <> y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 60 SECOND",
    "op_corr": f"{_BULK}{_RET}, dr AS (SELECT v, count(*) AS deg FROM (SELECT src AS v FROM er UNION ALL SELECT dst FROM er) GROUP BY v) SELECT round(corr(d.deg, dr.deg) * 1e6)::BIGINT AS r, round(regr_slope(dr.deg, d.deg) * 1e6)::BIGINT AS slope, count(*)::BIGINT AS n FROM d JOIN dr ON dr.v = d.v",
    "op_stream_batch_equal": "SELECT count(*)::BIGINT AS edges, 0::BIGINT AS only_stream, 0::BIGINT AS only_batch FROM (SELECT DISTINCT least(x.user_id, y.user_id), greatest(x.user_id, y.user_id) FROM events x JOIN events y ON x.event_type = y.event_type AND x.user_id <> y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 60 SECOND)",
    "op_asof_join": "SELECT event_id, lag(event_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS before FROM events",
    "op_lateral_topk": f"{_BULK} SELECT u, v, k::INT AS k FROM (SELECT u, v, row_number() OVER (PARTITION BY u ORDER BY v) AS k FROM a) WHERE k <= 3",
    "op_group_label_pairs": f"{_BULK}{_LAB} SELECT least(bu, bv) AS a, greatest(bu, bv) AS b, count(*)::BIGINT AS n FROM la WHERE u < v GROUP BY ALL",
    "op_distinct_agg": f"{_BULK}{_LAB} SELECT lu, lv, count(DISTINCT u)::BIGINT AS n FROM la GROUP BY lu, lv",
    "op_rollup": f"{_BULK}{_LAB} SELECT p_type, p_brand, sum(deg)::BIGINT AS arcs, grouping_id(p_type, p_brand)::BIGINT AS gid FROM ld GROUP BY ROLLUP (p_type, p_brand)",
    "op_cube": f"{_BULK}{_LAB} SELECT p_type, p_brand, sum(deg)::BIGINT AS arcs, grouping_id(p_type, p_brand)::BIGINT AS gid FROM ld GROUP BY CUBE (p_type, p_brand)",
    "op_grouping_sets": f"{_BULK}{_LAB} SELECT p_type, p_brand, sum(deg)::BIGINT AS arcs FROM ld GROUP BY GROUPING SETS ((p_type), (p_brand))",
    "op_pivot_labels": f"{_BULK}{_LAB} SELECT lu, " + ", ".join(f"count(*) FILTER (lv = '{k}')::BIGINT AS \"{k}\"" for k in ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")) + " FROM la GROUP BY lu",
    "op_unpivot_roles": f"{_BULK}{_TRI} SELECT 'm0' AS role, count(*)::BIGINT AS n, sum(m0)::BIGINT AS sum_v FROM t UNION ALL SELECT 'm1', count(*), sum(m1)::BIGINT FROM t UNION ALL SELECT 'm2', count(*), sum(m2)::BIGINT FROM t",
    "op_rank_degree": f"{_BULK}{_LAB} SELECT v, row_number() OVER (PARTITION BY p_type ORDER BY deg DESC, v)::INT AS rn, rank() OVER (PARTITION BY p_type ORDER BY deg DESC)::INT AS rk, dense_rank() OVER (PARTITION BY p_type ORDER BY deg DESC)::INT AS dr, ntile(4) OVER (PARTITION BY p_type ORDER BY deg DESC, v)::INT AS nt FROM ld",
    "op_lead_lag": "SELECT event_id, (lead(epoch_us(ts)) OVER w - epoch_us(ts))::BIGINT AS gap_us, lag(event_id) OVER w AS previous FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "op_running_edges": "SELECT month, sum(n) OVER (ORDER BY month)::BIGINT AS total FROM (SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n FROM orders GROUP BY 1)",
    "op_range_frame": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events",
    "op_topk_hubs": f"{_BULK} SELECT v, deg FROM d ORDER BY deg DESC, v LIMIT 10",
    "op_union": f"{_BULK}{_RET} SELECT src, dst FROM e UNION SELECT src, dst FROM er", "op_intersect": f"{_BULK}{_RET} SELECT src, dst FROM e INTERSECT SELECT src, dst FROM er", "op_except": f"{_BULK}{_RET} SELECT src, dst FROM e EXCEPT SELECT src, dst FROM er",
    "op_string_fn": "SELECT p_partkey, lpad(p_partkey::VARCHAR, 8, '0') AS padded, upper(substring(p_type, 1, 3)) AS short, length(p_brand)::INT AS len, regexp_extract(p_brand, '([0-9]+)', 1) AS digits FROM part",
    "op_date_fn": "SELECT strftime(ts, '%Y-%m-%d %H') AS hour, count(*)::BIGINT AS n FROM events GROUP BY 1",
    "op_math_fn": f"{_BULK} SELECT v, (deg * (deg - 1) // 2)::BIGINT AS choose2, greatest(deg, 3)::BIGINT AS at_least, (v % 7)::BIGINT AS r FROM d",
    "op_array_intersect": f"{_BULK} SELECT src, dst, (SELECT count(*) FROM a x JOIN a y ON x.v = y.v WHERE x.u = src AND y.u = dst)::INT AS n FROM e",
    "op_array_except_trim": f"{_BULK} SELECT src, dst, count(x.v) FILTER (y.v IS NULL)::INT AS n FROM e LEFT JOIN a x ON x.u = src AND x.v > dst LEFT JOIN a y ON y.u = dst AND y.v = x.v GROUP BY src, dst",
    "op_map_roles": f"{_BULK}{_TRI} SELECT m0 AS a, m1 AS b, 3 AS k FROM t",
    "op_json_props": "SELECT event_id, json_extract_string(props, '$.k')::INT AS k FROM events",
    "op_page_links": "SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages",
    "op_conversation_chain": "SELECT a, b, count(*)::BIGINT AS n FROM (SELECT role AS a, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations) WHERE b IS NOT NULL GROUP BY a, b",
    "op_fk_graph": "SELECT DISTINCT least(a, b)::BIGINT AS src, greatest(a, b)::BIGINT AS dst FROM (SELECT n_regionkey * 8 AS a, n_nationkey * 8 + 1 AS b FROM nation UNION ALL SELECT c_nationkey * 8 + 1, c_custkey * 8 + 2 FROM customer UNION ALL SELECT s_nationkey * 8 + 1, s_suppkey * 8 + 3 FROM supplier) WHERE a <> b",
    "op_doc_label_graph": "SELECT source, quality, count(*)::BIGINT AS n FROM documents JOIN labels USING (doc_id) GROUP BY ALL",
    "op_udtf_automorphisms": f"{_BULK}{_TRI} SELECT m0, m1, m2 FROM t UNION ALL SELECT m0, m2, m1 FROM t UNION ALL SELECT m1, m0, m2 FROM t UNION ALL SELECT m1, m2, m0 FROM t UNION ALL SELECT m2, m0, m1 FROM t UNION ALL SELECT m2, m1, m0 FROM t",
    "op_bip_degrees": "WITH e AS (SELECT DISTINCT l_partkey AS p, l_suppkey + 1000000000 AS s FROM lineitem WHERE l_returnflag = 'R') SELECT p AS v, count(*)::BIGINT AS deg FROM e GROUP BY p UNION ALL SELECT s, count(*) FROM e GROUP BY s",
    "op_sim_edges": "WITH s AS (SELECT vec_id AS k, list_transform(embedding, lambda v: v::DOUBLE) AS e FROM embeddings) SELECT x.k AS src, y.k AS dst FROM s x JOIN s y ON x.k < y.k WHERE list_sum(list_transform(list_zip(x.e, y.e), lambda p: p[1] * p[2])) / sqrt(list_sum(list_transform(x.e, lambda v: v * v)) * list_sum(list_transform(y.e, lambda v: v * v))) >= 0.3",
}
