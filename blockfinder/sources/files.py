"""Edge lists in files, blocks written for later use, and the timing sink."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "a long, b long"


def read_edges(spark: SparkSession, path: str, form: str = "parquet", separator: str = "\t", a: str = "a", b: str = "b") -> DataFrame:
    """(a, b) from Parquet, ORC, JSON, or CSV and TSV without a header; text is read with a fixed schema."""
    if form in ("csv", "tsv"):
        return spark.read.schema(EDGE_SCHEMA).csv(path, sep="," if form == "csv" else separator)
    reader = spark.read.schema(f"`{a}` long, `{b}` long") if form == "json" else spark.read
    return reader.format(form).load(path).select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b"))


def write_edges(edges: DataFrame, path: str, form: str = "parquet", separator: str = "\t") -> None:
    out = edges.write.mode("overwrite")
    if form in ("csv", "tsv"):
        out.csv(path, sep="," if form == "csv" else separator)
    else:
        out.format(form).save(path)


def write_blocks(blocks: DataFrame, path: str, depth: int = 3) -> None:
    """Blocks (id, block, path), in folders by the first steps of their path: nearby blocks lie together."""
    blocks.withColumn("part", F.substring(F.concat(F.lit("r"), "path"), 1, depth + 1)).write.mode("overwrite").partitionBy("part").parquet(path)


def save_arcs(arcs: DataFrame, name: str, buckets: int) -> None:
    """A bucketed table, sorted by ``src``: later layers join it without moving it."""
    arcs.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(name)


def run_only(df: DataFrame) -> None:
    """Run a plan without keeping its rows."""
    df.write.format("noop").mode("overwrite").save()
