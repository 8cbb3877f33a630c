"""Graphs that the given tables hold, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import generator, graph
from ..operators.graph import Graph

OFFSET = 1_000_000_000  # keeps the two sides of a bipartite graph apart
LEAST_LINE = 30


def table(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def coorder_pairs(spark: SparkSession, sf: str, column: str) -> DataFrame:
    return graph.shared_pairs(table(spark, sf, "lineitem"), F.col(column), F.col("l_orderkey"))


def coorder_sql(column: str) -> str:
    return f"SELECT DISTINCT a.n AS src, b.n AS dst FROM (SELECT DISTINCT {column} AS n, l_orderkey AS k FROM lineitem) a JOIN (SELECT DISTINCT {column} AS n, l_orderkey AS k FROM lineitem) b ON a.k = b.k WHERE a.n < b.n"


def arcs_sql(edges: str) -> str:
    return f"SELECT src, dst FROM ({edges}) e UNION ALL SELECT dst AS src, src AS dst FROM ({edges}) f"


def graph_ctes(edges: str) -> str:
    """CTEs e (edges), arcs, deg, tot (m) for the graph with these edges."""
    return f"e AS ({edges}), arcs AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), deg AS (SELECT src AS id, count(*) AS deg FROM arcs GROUP BY src), tot AS (SELECT count(*) AS m FROM e)"


SUPPLIER = coorder_sql("l_suppkey")
PART = coorder_sql("l_partkey")
CUSTOMER_SUPPLIER = f"SELECT DISTINCT o_custkey AS src, l_suppkey + {OFFSET} AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
USER_KEY = f"SELECT DISTINCT user_id AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) + {OFFSET} AS dst FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL"


def supplier_graph(spark: SparkSession, sf: str) -> Graph:
    return graph.build(coorder_pairs(spark, sf, "l_suppkey"))


def sharing_suppliers(spark: SparkSession, sf: str) -> DataFrame:
    """(id) of suppliers with an order that another supplier has a line of, too."""
    lines = table(spark, sf, "lineitem").select(F.col("l_suppkey").cast("long").alias("id"), "l_orderkey").where("id is not null")
    shared = lines.groupBy("l_orderkey").agg(F.min("id").alias("least"), F.max("id").alias("most")).where("least < most")
    return lines.join(shared, "l_orderkey", "left_semi").select("id").distinct()


def part_graph(spark: SparkSession, sf: str) -> Graph:
    return graph.build(coorder_pairs(spark, sf, "l_partkey"))


def customer_supplier(spark: SparkSession, sf: str) -> DataFrame:
    lines = table(spark, sf, "lineitem").select("l_orderkey", "l_suppkey")
    orders = table(spark, sf, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    return lines.join(orders, "l_orderkey").select(F.col("o_custkey").alias("a"), (F.col("l_suppkey") + OFFSET).alias("b"))


def user_key(spark: SparkSession, sf: str) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("long")
    return table(spark, sf, "events").select(F.col("user_id").alias("a"), (k + OFFSET).alias("b"), F.col("ts").cast("timestamp").alias("ts")).where("b is not null")


def document_lines(spark: SparkSession, sf: str) -> DataFrame:
    lines = table(spark, sf, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line"))
    return lines.where(F.length("line") >= LEAST_LINE).distinct()


def shared_lines(spark: SparkSession, sf: str) -> DataFrame:
    """(doc_id, line) of lines that two or more documents hold."""
    lines = document_lines(spark, sf)
    return lines.join(lines.groupBy("line").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("line"), "line").select("doc_id", "line")


def line_graph(spark: SparkSession, sf: str) -> Graph:
    """Documents (all of them) and shared lines as nodes of one graph; no pair of documents is listed."""
    pairs = shared_lines(spark, sf).select(F.col("doc_id").cast("long").alias("a"), (F.pmod(F.xxhash64("line"), F.lit(1 << 61)) + (1 << 62)).alias("b"))
    return graph.build(pairs, table(spark, sf, "documents").select(F.col("doc_id").alias("id")))


def planted(spark: SparkSession, sf: str, name: str, key: str, block: str | None = None, ratio: float = 2.5, seed: int = 0, mean_degree: float = 36.0, heterogeneity: float = 3.0, method: str = "skip") -> tuple[generator.Params, Graph]:
    """A graph from the block model over a table's ids; a column's values are the blocks, or drawn ones."""
    rows = table(spark, sf, name)
    if block is None:
        nodes = rows.select(F.col(key).cast("long").alias("id")).distinct()
    elif rows.schema[block].dataType.typeName() == "string":
        # One row for each block's name, numbered in order; a null is a block like any other.
        named = rows.select(F.col(key).cast("long").alias("id"), F.coalesce(F.col(block), F.lit("")).alias("name"))
        codes = named.select("name").distinct().select("name", (F.row_number().over(Window.orderBy("name")) - 1).alias("b"))
        nodes = named.join(codes, "name").select("id", "b")
    else:
        nodes = rows.select(F.col(key).cast("long").alias("id"), F.col(block).cast("int").alias("b"))
    params = generator.benchmark_params(nodes, ratio=ratio, heterogeneity=heterogeneity, mean_degree=mean_degree, seed=seed, block=None if block is None else "b")
    return params, graph.build(generator.sample(params, method, seed), nodes, "src", "dst")
