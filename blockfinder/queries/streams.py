"""Streaming: what can be said in SQL about batches, and the streams themselves."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import graph, metrics
from ..streaming import jobs, updates
from . import query
from .tables import CUSTOMER_SUPPLIER, graph_ctes, planted, table

MONTHS = "SELECT strftime(o_orderdate, '%Y-%m') AS month, o_custkey AS a, l_suppkey AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey"


def dated(spark, sf):
    orders = table(spark, sf, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("a"), "o_orderdate")
    return orders.join(table(spark, sf, "lineitem").select("l_orderkey", F.col("l_suppkey").alias("b")), "l_orderkey")


@query(f"SELECT a AS id, month, count(*) AS more FROM (SELECT a, b, min(month) AS month FROM ({MONTHS}) GROUP BY a, b) GROUP BY 1, 2")
def degree_delta_by_month(spark, sf):
    """New distinct edges of each customer in the month when they first appear."""
    first = dated(spark, sf).groupBy("a", "b").agg(F.min(F.date_format("o_orderdate", "yyyy-MM")).alias("month"))
    return first.groupBy(F.col("a").alias("id"), "month").agg(F.count(F.lit(1)).alias("more"))


DAY = "SELECT DISTINCT o_custkey AS src, l_suppkey + 1000000000 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE CAST(o_orderdate AS DATE) = DATE '1995-06-15'"


def day_batch(spark, sf):
    rows = dated(spark, sf).where(F.to_date("o_orderdate") == F.lit("1995-06-15"))
    return graph.canonical(rows.select("a", (F.col("b") + 1_000_000_000).alias("b")))


@query(f"SELECT src AS id FROM ({DAY}) UNION SELECT dst FROM ({DAY})")
def touched_nodes_day(spark, sf):
    return updates.touched(day_batch(spark, sf))


@query(f"WITH {graph_ctes(CUSTOMER_SUPPLIER)}, t AS (SELECT src AS id FROM ({DAY}) x UNION SELECT dst FROM ({DAY}) y), near AS (SELECT id FROM t UNION SELECT dst FROM arcs JOIN t ON arcs.src = t.id) SELECT arcs.src, arcs.dst FROM arcs JOIN near a ON arcs.src = a.id JOIN near b ON arcs.dst = b.id")
def affected_region_day(spark, sf):
    from .tables import customer_supplier

    g = graph.build(customer_supplier(spark, sf))
    return updates.affected(g, day_batch(spark, sf), 1)[1].select("src", "dst")


@query("SELECT user_id AS a, count(*) AS n, strftime(date_trunc('day', ts), '%Y-%m-%d') AS day FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY 1, 3")
def tumbling_events(spark, sf):
    rows = jobs.run(jobs.windowed(jobs.event_edges(spark, sf), "tumbling"), "complete", spark)
    return rows.select("a", "n", F.date_format("start", "yyyy-MM-dd").alias("day"))


@query("SELECT a, count(*) AS n, strftime(s, '%Y-%m-%d %H') AS start FROM (SELECT user_id AS a, unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR]) AS s FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL) x GROUP BY 1, 3")
def sliding_events(spark, sf):
    rows = jobs.run(jobs.windowed(jobs.event_edges(spark, sf), "sliding"), "complete", spark)
    return rows.select("a", "n", F.date_format("start", "yyyy-MM-dd HH").alias("start"))


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id AS a, count(*) AS n, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start FROM s GROUP BY user_id, k")
def session_events(spark, sf):
    edges = jobs.event_edges_batch(spark, sf)
    rows = edges.groupBy("a", F.session_window("event_time", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return rows.select("a", "n", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"))


@query("SELECT user_id AS id, count(*) AS deg FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY 1")
def stream_degrees(spark, sf):
    """Counts held in the state store; the last one of each node."""
    return jobs.run(jobs.stateful_degrees(jobs.event_edges(spark, sf)), "update", spark).groupBy("id").agg(F.max("deg").alias("deg"))


@query()
def stream_dedupe(spark, sf):
    return jobs.run(jobs.without_repeats(jobs.event_edges(spark, sf)), "append", spark).select("a", "b").distinct()


@query("SELECT DISTINCT c.user_id AS user, c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE json_extract_string(c.props, '$.k') IS NOT NULL AND json_extract_string(p.props, '$.k') IS NOT NULL")
def stream_stream_join(spark, sf):
    return jobs.run(jobs.click_then_purchase(jobs.event_edges(spark, sf)), "append", spark)


@query("SELECT event_id, user_id % 7 AS block FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL")
def stream_static_join(spark, sf):
    blocks = table(spark, sf, "events").select(F.col("user_id").alias("id")).distinct().withColumn("block", F.col("id") % 7)
    return jobs.run(jobs.with_blocks(jobs.event_edges(spark, sf), blocks), "append", spark).select("event_id", "block")


def grown(spark, sf, mode):
    """A separated planted graph whose last tenth of edges comes in two batches, against a full run."""
    p, g = planted(spark, sf, "customer", "c_custkey", "c_mktsegment", ratio=8.0, mean_degree=20.0)
    edges = g.arcs.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"))
    part = F.pmod(F.xxhash64("a", "b"), F.lit(20))
    state = updates.start(graph.build(edges.where(part > 1)), "cut", (128, 64, 32))
    for k in (0, 1):
        state = updates.apply_batch(state, edges.where(part == k), mode)
    full = updates.start(graph.build(edges), "cut", (128, 64, 32))
    row = metrics.scores(full.blocks, state.blocks)
    far = state.embedding.select("id", "v").join(full.embedding.select("id", F.col("v").alias("u")), "id").select(F.max(F.aggregate(F.zip_with("v", "u", lambda x, y: F.abs(x - y).cast("double")), F.lit(0.0), lambda s, x: F.greatest(s, x))).alias("far")).first()["far"]
    return spark.createDataFrame([(mode, float(row["acc"]), float(row["ari"]), row["k_true"], row["k_found"], round(far, 6))], "mode string, agreement double, ari double, k_full long, k_stream long, largest_difference double")


@query()
def stream_refresh_ball(spark, sf):
    return grown(spark, sf, "ball")


@query()
def stream_refresh_touched(spark, sf):
    return grown(spark, sf, "touched")


@query("SELECT prefix AS path, count(*) AS n FROM (SELECT substr(path, 1, i) AS prefix FROM (SELECT right('00000' || bin(c_custkey % 32), 5) AS path FROM customer) p CROSS JOIN (SELECT unnest(range(0, 6)) AS i) r) GROUP BY prefix")
def path_prefix_deltas(spark, sf):
    placed = table(spark, sf, "customer").select(F.col("c_custkey").alias("id"), F.lpad(F.bin(F.col("c_custkey") % 32), 5, "0").alias("path"))
    return updates.prefix_counts(placed)
