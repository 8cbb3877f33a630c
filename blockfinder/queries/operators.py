"""The operators that users of the methods need around them, on the given tables, each with SQL."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.rng import hash01, hash01_sql
from ..operators import graph
from . import query
from .tables import PART, coorder_pairs, graph_ctes, table

K = "CAST(json_extract_string(props, '$.k') AS BIGINT)"


@query("SELECT DISTINCT a.n AS src, b.n AS dst FROM (SELECT l_partkey AS n, l_orderkey AS k FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_size < 20) a JOIN (SELECT l_partkey AS n, l_orderkey AS k FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_size < 20) b ON a.k = b.k WHERE a.n < b.n")
def op_scan_pushdown(spark, sf):
    small = table(spark, sf, "part").where("p_size < 20").select(F.col("p_partkey").alias("l_partkey"))
    lines = table(spark, sf, "lineitem").select("l_partkey", "l_orderkey").join(small, "l_partkey", "left_semi")
    return graph.canonical(graph.shared_pairs(lines, F.col("l_partkey"), F.col("l_orderkey")))


@query("SELECT vec_id AS id, round(list_dot_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[])), 6) AS dot, round(CAST(embedding[1] AS DOUBLE) * 2, 6) AS twice FROM embeddings")
def op_projection_vectors(spark, sf):
    from ..functions.vectors import dot, scaled

    v = F.col("embedding")
    return table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.round(dot(v, v), 6).alias("dot"), F.round(scaled(v, F.lit(2.0))[0], 6).alias("twice"))


@query("SELECT label, round(avg(CAST(embedding[1] AS DOUBLE)), 6) + 0.0 AS first, round(avg(CAST(embedding[2] AS DOUBLE)), 6) + 0.0 AS second FROM embeddings GROUP BY label")
def op_agg_vector_mean(spark, sf):
    return table(spark, sf, "embeddings").groupBy("label").agg(*[(F.round(F.avg(F.col("embedding")[k].cast("double")), 6) + 0.0).alias(n) for k, n in enumerate(("first", "second"))])


COUNTS_SQL = "SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"


def customers_by_nation(spark, sf, hint):
    nations = table(spark, sf, "nation").select("n_nationkey", "n_name")
    return table(spark, sf, "customer").join(nations.hint(hint), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))


for kind, hint in {"broadcast": "broadcast", "shuffle_hash": "shuffle_hash", "sort_merge": "merge"}.items():
    query(COUNTS_SQL, f"op_join_{kind}")(lambda spark, sf, hint=hint: customers_by_nation(spark, sf, hint))


@query("SELECT x.c_custkey AS a, y.s_suppkey AS b FROM customer x JOIN supplier y ON x.c_acctbal < y.s_acctbal")
def op_join_theta(spark, sf):
    few = table(spark, sf, "supplier").select(F.col("s_suppkey").alias("b"), "s_acctbal")
    return table(spark, sf, "customer").join(few, F.col("c_acctbal") < F.col("s_acctbal")).select(F.col("c_custkey").alias("a"), "b")


RANGE_SQL = "r AS (SELECT c_custkey AS id, c_nationkey AS b, sum(c_custkey) OVER (PARTITION BY c_nationkey ORDER BY c_custkey) - c_custkey AS lo, sum(c_custkey) OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS hi FROM customer)"


@query(f"WITH {RANGE_SQL}, u AS (SELECT s_suppkey, s_nationkey AS b, s_suppkey * 37 % 1000 AS aim FROM supplier) SELECT s_suppkey, id AS c_custkey FROM u JOIN r ON u.b = r.b AND aim >= lo AND aim < hi")
def op_join_range(spark, sf):
    w = Window.partitionBy("c_nationkey").orderBy("c_custkey").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    spans = table(spark, sf, "customer").select("c_custkey", F.col("c_nationkey").alias("b"), F.sum("c_custkey").over(w).alias("hi")).withColumn("lo", F.col("hi") - F.col("c_custkey"))
    width = 200
    spans = spans.where("lo < 1000").withColumn("bucket", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.least(F.col("hi"), F.lit(1000)) / width))))
    aims = table(spark, sf, "supplier").select("s_suppkey", F.col("s_nationkey").alias("b"), (F.col("s_suppkey") * 37 % 1000).alias("aim")).withColumn("bucket", F.floor(F.col("aim") / width))
    return aims.join(spans, ["b", "bucket"]).where("aim >= lo and aim < hi").select("s_suppkey", "c_custkey")


@query("SELECT e.event_id, (SELECT max_by(p.event_id, (p.ts, p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND (p.ts, p.event_id) < (e.ts, e.event_id)) AS last_purchase FROM events e WHERE e.event_type = 'click'")
def op_join_asof(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return table(spark, sf, "events").select("event_id", "event_type", last.alias("last_purchase")).where("event_type = 'click'").select("event_id", "last_purchase")


@query(f"WITH x AS (SELECT user_id, {K} AS k, ts FROM events) SELECT DISTINCT a.user_id AS src, b.user_id AS dst FROM x a JOIN x b ON a.k = b.k AND a.user_id < b.user_id AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR")
def op_join_interval(spark, sf):
    rows = table(spark, sf, "events").select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t")).where("k is not null")
    hour = 3_600_000_000
    a = rows.select(F.col("user_id").alias("src"), "k", F.col("t").alias("t0"), F.explode(F.sequence(F.floor(F.col("t") / hour) - 1, F.floor(F.col("t") / hour) + 1)).alias("slot"))
    b = rows.select(F.col("user_id").alias("dst"), "k", F.col("t").alias("t1"), F.floor(F.col("t") / hour).alias("slot"))
    return a.join(b, ["k", "slot"]).where((F.col("src") < F.col("dst")) & (F.abs(F.col("t1") - F.col("t0")) <= hour)).select("src", "dst").distinct()


@query("SELECT s_suppkey FROM supplier WHERE s_suppkey IN (SELECT l_suppkey FROM lineitem WHERE l_quantity > 49)")
def op_join_semi(spark, sf):
    return table(spark, sf, "supplier").join(table(spark, sf, "lineitem").where("l_quantity > 49").select(F.col("l_suppkey").alias("s_suppkey")), "s_suppkey", "left_semi").select("s_suppkey")


@query("SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 25)")
def op_join_anti(spark, sf):
    return table(spark, sf, "part").select("p_partkey").join(table(spark, sf, "lineitem").where("l_quantity > 25").select(F.col("l_partkey").alias("p_partkey")), "p_partkey", "left_anti")


@query("SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def op_join_outer(spark, sf):
    per = table(spark, sf, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("o_orderkey").alias("orders"))
    return table(spark, sf, "customer").select("c_custkey").join(per, "c_custkey", "left").select("c_custkey", F.coalesce("orders", F.lit(0)).alias("orders"))


@query("SELECT o_custkey, count(DISTINCT l_suppkey) AS suppliers FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey")
def op_agg_distinct(spark, sf):
    lines = table(spark, sf, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_suppkey")
    return table(spark, sf, "orders").select("o_orderkey", "o_custkey").join(lines, "o_orderkey").groupBy("o_custkey").agg(F.countDistinct("l_suppkey").alias("suppliers"))


@query()
def op_agg_distinct_approx(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


def placed(spark, sf):
    nations = table(spark, sf, "nation").join(table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    return table(spark, sf, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).select("r_name", "n_name", "c_mktsegment")


PLACED = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


@query(f"SELECT r_name, n_name, count(*) AS n {PLACED} GROUP BY ROLLUP (r_name, n_name)")
def op_rollup(spark, sf):
    return placed(spark, sf).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT r_name, c_mktsegment, count(*) AS n {PLACED} GROUP BY CUBE (r_name, c_mktsegment)")
def op_cube(spark, sf):
    return placed(spark, sf).cube("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT r_name, c_mktsegment, count(*) AS n {PLACED} GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")
def op_grouping_sets(spark, sf):
    return placed(spark, sf).groupingSets([["r_name"], ["c_mktsegment"], []], "r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT c_custkey, n_name FROM (SELECT o_custkey AS c_custkey, n_name, row_number() OVER (PARTITION BY o_custkey ORDER BY count(*) DESC, n_name) AS k FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY o_custkey, n_name) x WHERE k = 1")
def op_agg_argmax(spark, sf):
    nation = table(spark, sf, "supplier").join(F.broadcast(table(spark, sf, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").alias("l_suppkey"), "n_name", "n_nationkey")
    lines = table(spark, sf, "lineitem").select("l_orderkey", "l_suppkey").join(nation, "l_suppkey").join(table(spark, sf, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c_custkey")), "l_orderkey")
    counts = lines.groupBy("c_custkey", "n_name").count()
    order = Window.partitionBy("c_custkey").orderBy(F.desc("count"), "n_name")
    return counts.withColumn("k", F.row_number().over(order)).where("k = 1").select("c_custkey", "n_name")


@query(f"WITH {graph_ctes(PART)} SELECT min(deg) AS low, quantile_cont(deg, 0.5) AS median, max(deg) AS high, round(avg(deg), 6) AS mean FROM deg")
def op_agg_percentile(spark, sf):
    deg = graph.degrees(graph.both_ways(graph.canonical(coorder_pairs(spark, sf, "l_partkey"))))
    return deg.agg(F.min("deg").alias("low"), F.percentile("deg", 0.5).alias("median"), F.max("deg").alias("high"), F.round(F.avg("deg"), 6).alias("mean"))


SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")


@query("SELECT r_name, " + ", ".join(f"count(*) FILTER (c_mktsegment = '{s}') AS {s.lower()}" for s in SEGMENTS) + f" {PLACED} GROUP BY r_name")
def op_pivot(spark, sf):
    wide = placed(spark, sf).groupBy("r_name").pivot("c_mktsegment", list(SEGMENTS)).agg(F.count(F.lit(1)))
    return wide.select("r_name", *[F.coalesce(F.col(s), F.lit(0)).alias(s.lower()) for s in SEGMENTS])


@query("SELECT src, dst, rank FROM (SELECT a.l_partkey AS src, b.l_partkey AS dst, row_number() OVER (PARTITION BY a.l_partkey ORDER BY count(DISTINCT a.l_orderkey) DESC, b.l_partkey) AS rank FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey GROUP BY 1, 2) x WHERE rank <= 3")
def op_window_rank(spark, sf):
    rows = table(spark, sf, "lineitem").select("l_orderkey", "l_partkey").distinct()
    both = rows.select(F.col("l_partkey").alias("src"), "l_orderkey").join(rows.select(F.col("l_partkey").alias("dst"), "l_orderkey"), "l_orderkey").where("src <> dst").groupBy("src", "dst").count()
    return both.withColumn("rank", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("count"), "dst")).cast("long")).where("rank <= 3").select("src", "dst", "rank")


@query("SELECT event_id, date_diff('second', lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id), ts) AS gap, first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS first_id FROM events")
def op_window_analytic(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    t = F.unix_seconds(F.col("ts").cast("timestamp"))
    return table(spark, sf, "events").select("event_id", (t - F.lag(t).over(w)).alias("gap"), F.first("event_id").over(w).alias("first_id"))


@query("SELECT o_custkey, o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS so_far, count(*) OVER (PARTITION BY o_custkey ORDER BY CAST(epoch(o_orderdate) AS BIGINT) RANGE BETWEEN 2592000 PRECEDING AND CURRENT ROW) AS month FROM orders")
def op_window_frame(spark, sf):
    t = F.unix_seconds(F.col("o_orderdate").cast("timestamp"))
    rows = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    span = Window.partitionBy("o_custkey").orderBy("t").rangeBetween(-2_592_000, Window.currentRow)
    return table(spark, sf, "orders").withColumn("t", t).select("o_custkey", "o_orderkey", F.count(F.lit(1)).over(rows).alias("so_far"), F.count(F.lit(1)).over(span).alias("month"))


@query(f"WITH {graph_ctes(PART)} SELECT id, deg FROM deg ORDER BY deg DESC, id LIMIT 10")
def op_topk(spark, sf):
    return graph.degrees(graph.both_ways(graph.canonical(coorder_pairs(spark, sf, "l_partkey")))).orderBy(F.desc("deg"), "id").limit(10)


def year_pairs(spark, sf, year):
    orders = table(spark, sf, "orders").where(F.year("o_orderdate") == year).select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("a"))
    return orders.join(table(spark, sf, "lineitem").select("l_orderkey", F.col("l_suppkey").alias("b")), "l_orderkey").select("a", "b").distinct()


YEAR = "SELECT DISTINCT o_custkey AS a, l_suppkey AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE year(o_orderdate) = {}"


@query(f"{YEAR.format(1997)} EXCEPT ALL {YEAR.format(1996)}")
def op_except_all(spark, sf):
    return year_pairs(spark, sf, 1997).exceptAll(year_pairs(spark, sf, 1996))


@query(f"{YEAR.format(1997)} INTERSECT {YEAR.format(1996)}")
def op_intersect(spark, sf):
    return year_pairs(spark, sf, 1997).intersect(year_pairs(spark, sf, 1996))


@query(f"SELECT a, b FROM ({YEAR.format(1997)}) UNION SELECT a, b FROM ({YEAR.format(1996)})")
def op_union(spark, sf):
    return year_pairs(spark, sf, 1997).unionByName(year_pairs(spark, sf, 1996)).distinct()


@query("SELECT regexp_extract(url, 'https?://([^/]+)', 1) AS host, count(*) AS pages FROM pages GROUP BY 1")
def op_strings(spark, sf):
    return table(spark, sf, "pages").groupBy(F.regexp_extract("url", "https?://([^/]+)", 1).alias("host")).agg(F.count(F.lit(1)).alias("pages"))


@query("SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS orders, CAST(max(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE))) AS INTEGER) AS last_day FROM orders GROUP BY 1")
def op_dates(spark, sf):
    return table(spark, sf, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("orders"), F.max(F.datediff("o_orderdate", F.lit("1992-01-01"))).alias("last_day"))


@query("SELECT c_custkey, round(sqrt(abs(c_acctbal)), 6) AS root, round(ln(1 + abs(c_acctbal)), 6) AS log, round(tanh(c_acctbal / 1000), 6) + 0.0 AS act FROM customer")
def op_math(spark, sf):
    x = F.col("c_acctbal")
    return table(spark, sf, "customer").select("c_custkey", F.round(F.sqrt(F.abs(x)), 6).alias("root"), F.round(F.log1p(F.abs(x)), 6).alias("log"), (F.round(F.tanh(x / 1000), 6) + 0.0).alias("act"))


@query(f"WITH {graph_ctes(PART)}, h AS (SELECT deg // 50 AS bin, count(*) AS n FROM deg GROUP BY 1) SELECT string_agg(CAST(bin AS VARCHAR) || ':' || CAST(n AS VARCHAR), ',' ORDER BY bin) AS histogram FROM h")
def op_maps(spark, sf):
    deg = graph.degrees(graph.both_ways(graph.canonical(coorder_pairs(spark, sf, "l_partkey"))))
    bins = deg.groupBy(F.floor(F.col("deg") / 50).cast("long").alias("bin")).count()
    held = bins.agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("bin", "count")))).alias("m"))
    return held.select(F.concat_ws(",", F.transform(F.map_entries("m"), lambda e: F.concat(e["key"].cast("string"), F.lit(":"), e["value"].cast("string")))).alias("histogram"))


@query(f"SELECT event_type, {K} AS k, count(*) AS n FROM events GROUP BY 1, 2")
def op_json(spark, sf):
    k = F.from_json("props", "k long")["k"]
    return table(spark, sf, "events").groupBy("event_type", k.alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("WITH t AS (SELECT path, substr(path, 1, i) AS prefix FROM (SELECT right('0000000' || bin(c_custkey % 128), 7) AS path FROM customer) p CROSS JOIN (SELECT unnest(range(0, 8)) AS i) r) SELECT prefix, count(*) AS n FROM t GROUP BY prefix")
def op_struct_prefixes(spark, sf):
    """Members of all nodes of a binary tree, from leaves: each path's prefixes."""
    path = F.lpad(F.bin(F.col("c_custkey") % 128), 7, "0")
    prefixes = table(spark, sf, "customer").select(path.alias("path")).select(F.explode(F.transform(F.sequence(F.lit(0), F.lit(7)), lambda i: F.struct(F.substring("path", F.lit(1), i).alias("prefix"), i.alias("depth")))).alias("node"))
    return prefixes.groupBy(F.col("node.prefix").alias("prefix")).agg(F.count(F.lit(1)).alias("n"))


TREE_SQL = "WITH RECURSIVE up(id, top) AS (SELECT p_partkey, p_partkey FROM part UNION ALL SELECT id, top // 2 FROM up WHERE top > 1) SELECT id, count(*) AS steps, min(top) AS top FROM up GROUP BY id"


@query(TREE_SQL)
def op_recursive(spark, sf):
    table(spark, sf, "part").createOrReplaceTempView("bf_part")
    return spark.sql("WITH RECURSIVE up(id, top) AS (SELECT p_partkey, p_partkey FROM bf_part UNION ALL SELECT id, top DIV 2 FROM up WHERE top > 1) SELECT id, count(*) AS steps, min(top) AS top FROM (SELECT * FROM up LIMIT ALL) GROUP BY id")


@query(f"SELECT c_custkey FROM customer WHERE {hash01_sql(3, 'c_custkey')} < 0.1")
def op_hash_sample(spark, sf):
    """A stable sample of a tenth."""
    return table(spark, sf, "customer").where(hash01(3, F.col("c_custkey")) < 0.1).select("c_custkey")


@query(f"SELECT c_custkey, {hash01_sql(5, 'c_custkey', '2')} AS u, CAST(c_nationkey * (c_nationkey - 1) // 2 AS BIGINT) AS pairs FROM customer")
def op_sql_functions(spark, sf):
    from ..functions.vectors import register

    register(spark)
    table(spark, sf, "customer").createOrReplaceTempView("bf_customer")
    return spark.sql("SELECT c_custkey, bf_hash01(5, c_custkey, 2) AS u, bf_pairs(c_nationkey) AS pairs FROM bf_customer")


@query("SELECT label, count(*) AS n, round(avg(CAST(embedding[1] AS DOUBLE)), 5) + 0.0 AS first FROM embeddings GROUP BY label")
def op_grouped_map(spark, sf):
    def mean(key, rows):
        import numpy as np

        v = rows["embedding"].combine_chunks()
        z = v.flatten().to_numpy(zero_copy_only=False).reshape(len(v), -1).astype(np.float64)
        return pa.table({"label": pa.array([key[0].as_py()], pa.int32()), "n": [len(v)], "first": [float(z[:, 0].mean())]})

    out = table(spark, sf, "embeddings").groupBy("label").applyInArrow(mean, "label int, n long, first double")
    return out.select("label", "n", (F.round("first", 5) + 0.0).alias("first"))


@query("SELECT label, round(sum(CAST(embedding[1] AS DOUBLE)), 5) + 0.0 AS total FROM embeddings GROUP BY label")
def op_udaf(spark, sf):
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("double")
    def total(x: pd.Series) -> float:
        return float(x.astype("f8").sum())

    return table(spark, sf, "embeddings").groupBy("label").agg((F.round(total(F.col("embedding")[0]), 5) + 0.0).alias("total"))


@query("SELECT vec_id AS id, round(CAST(embedding[1] AS DOUBLE) * 0.5 + CAST(embedding[2] AS DOUBLE) * 0.25, 6) + 0.0 AS y FROM embeddings")
def op_udf_arrow(spark, sf):
    """A layer's multiplication as a vectorised function."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("double")
    def times(v: pd.Series) -> pd.Series:
        return v.map(lambda x: float(x[0]) * 0.5 + float(x[1]) * 0.25)

    return table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), (F.round(times("embedding"), 6) + 0.0).alias("y"))


@query("SELECT c_nationkey AS nation, count(*) AS n, min(c_custkey) AS least FROM customer GROUP BY 1")
def op_udtf(spark, sf):
    """A set finished by a table function that gets the rows of each set."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="nation: int, n: bigint, least: bigint")
    class Summary:
        def __init__(self):
            self.nation, self.n, self.least = None, 0, None

        def eval(self, row):
            self.nation, self.n = row["c_nationkey"], self.n + 1
            self.least = row["c_custkey"] if self.least is None else min(self.least, row["c_custkey"])

        def terminate(self):
            if self.n:
                yield self.nation, self.n, self.least

    spark.udtf.register("bf_summary", Summary)
    table(spark, sf, "customer").select("c_custkey", "c_nationkey").createOrReplaceTempView("bf_customers")
    return spark.sql("SELECT * FROM bf_summary(TABLE(bf_customers) PARTITION BY c_nationkey)")
