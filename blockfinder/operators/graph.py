"""Graphs as tables: canonical edges, arcs in both directions with both degrees, and nodes."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.state import settle, swept, written


@dataclass(frozen=True)
class Graph:
    """``nodes``: (id, deg). ``arcs``: (src, dst, dsrc, ddst), both directions, degrees of both ends. n nodes, m edges."""

    nodes: DataFrame
    arcs: DataFrame
    n: int
    m: int


def canonical(pairs: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(src, dst) with src < dst, each once. Loops and pairs with a null go."""
    a, b = F.col(a).cast("long"), F.col(b).cast("long")
    return pairs.select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"), (a.isNotNull() & b.isNotNull()).alias("whole")).where("whole and src < dst").select("src", "dst").distinct()


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def degrees(arcs: DataFrame) -> DataFrame:
    return arcs.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("deg"))


def with_degrees(arcs: DataFrame, deg: DataFrame) -> DataFrame:
    """Both joins are on the end's id; the second leaves the arcs clustered by ``src``."""
    at_dst = arcs.join(deg.select(F.col("id").alias("dst"), F.col("deg").alias("ddst")), "dst")
    return at_dst.join(deg.select(F.col("id").alias("src"), F.col("deg").alias("dsrc")), "src").select("src", "dst", "dsrc", "ddst")


def build(pairs: DataFrame, nodes: DataFrame | None = None, a: str = "a", b: str = "b") -> Graph:
    """From any table of pairs. ``nodes`` (id) adds nodes without edges, which get degree 0."""
    edges = written(canonical(pairs, a, b))
    deg = degrees(both_ways(edges))
    if nodes is not None:
        every = nodes.select(F.col("id").cast("long").alias("id")).where("id is not null").distinct()
        deg = every.join(deg, "id", "full_outer").select("id", F.coalesce("deg", F.lit(0)).cast("long").alias("deg"))
    deg = settle(deg)
    arcs = written(with_degrees(both_ways(edges), deg))
    swept(arcs.sparkSession)
    return Graph(deg, arcs, deg.count(), edges.count())


def describe_df(g: Graph) -> DataFrame:
    """One row: nodes, edges, least and largest degree, density."""
    n = F.lit(float(g.n))
    return g.nodes.agg(
        F.count(F.lit(1)).alias("n"), (F.sum("deg") / 2).cast("long").alias("m"), F.min("deg").alias("deg_min"), F.max("deg").alias("deg_max"), F.round(F.sum("deg") / (n * (n - 1)), 6).alias("density")
    )


def shared_pairs(df: DataFrame, node: Column, key: Column) -> DataFrame:
    """(a, b): all pairs of nodes that share a key. The table is made distinct first: repeated rows would square.

    For keys that few nodes share; where one may be in a large part of all rows, use keys as nodes of their own.
    """
    rows = df.select(node.cast("long").alias("node"), key.alias("key")).where("node is not null and key is not null").distinct()
    left, right = rows.select(F.col("node").alias("a"), "key"), rows.select(F.col("node").alias("b"), "key")
    return left.join(right, "key").where("a < b").select("a", "b")


def crowded(df: DataFrame, node: Column, key: Column, most: int) -> DataFrame:
    """Keys with over ``most`` nodes, to be reported: (key, n)."""
    return df.select(node.alias("node"), key.alias("key")).where("node is not null and key is not null").distinct().groupBy("key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > most)


def isolated(g: Graph) -> DataFrame:
    return g.nodes.where("deg = 0").select("id")


def neighbourhood(arcs: DataFrame, seeds: DataFrame, hops: int) -> DataFrame:
    """(id, hop): what is reached from ``seeds`` (id) in at most ``hops`` steps, with the least number of steps."""
    seen = seeds.select("id").distinct().withColumn("hop", F.lit(0))
    front = seen
    for k in range(1, hops + 1):
        found = arcs.join(front.select(F.col("id").alias("src")), "src", "left_semi").select(F.col("dst").alias("id")).distinct()
        front = found.join(seen, "id", "left_anti").withColumn("hop", F.lit(k))
        seen = seen.unionByName(front)
    return seen


def core_step(edges: DataFrame, k: int) -> DataFrame:
    """One step towards the k-core: edges between nodes of degree at least k."""
    strong = degrees(both_ways(edges)).where(F.col("deg") >= k).select("id")
    return edges.join(strong.withColumnRenamed("id", "src"), "src", "left_semi").join(strong.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst")
