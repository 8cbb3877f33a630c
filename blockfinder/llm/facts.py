"""What SQL can say about the operators' results, as queries of their own: columns and laws of ``op1``, ``op8`` and ``op10``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import media, quality, sharding

WORDS = "regexp_extract_all(t, '[^\\x20\\x09-\\x0D]+')"
LINES = "list_filter(string_split(t, chr(10)), lambda l: regexp_matches(l, '[^\\x20\\x09-\\x0D]'))"


def laws_of_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(shard, gapless, level, together): slots run from 0, loads differ by no more than the largest group, and no text is in two shards."""
    rows = sharding.query(spark, sf_dir).persist()
    most = rows.groupBy("text_crc32", "size").agg(F.sum("size").alias("whole"), F.countDistinct("shard").alias("shards")).agg(F.max("whole").alias("most"), F.max("shards").alias("spread"))
    loads = rows.groupBy("shard").agg(F.sum("size").alias("load"), (F.count(F.lit(1)) == F.countDistinct("slot")).alias("once"), (F.max("slot") == F.count(F.lit(1)) - 1).alias("last"))
    ends = loads.agg(F.min("load").alias("least_load"), F.max("load").alias("most_load"))
    every = loads.join(F.broadcast(ends.crossJoin(most)))  # single rows
    return every.select("shard", (F.col("once") & F.col("last")).alias("gapless"), (F.col("most_load") - F.col("least_load") <= F.col("most")).alias("level"), (F.col("spread") == 1).alias("together"))


def sizes_of_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media.query(spark, sf_dir).select("doc_id", "n_bytes", "payload_bytes")


def base_of_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.query(spark, sf_dir).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


QUERIES = {"laws_of_shards": laws_of_shards, "sizes_of_media": sizes_of_media, "base_of_quality_rules": base_of_quality_rules}
ORACLES = {
    "laws_of_shards": "SELECT CAST(range AS INTEGER) AS shard, true AS gapless, true AS level, true AS together FROM range(16)",
    "sizes_of_media": "SELECT doc_id, CAST(n AS BIGINT) AS n_bytes, CAST(greatest(64, (n + 63) // 64 * 64) AS BIGINT) AS payload_bytes FROM (SELECT doc_id, octet_length(encode(coalesce(text, ''))) AS n FROM documents) x",
    "base_of_quality_rules": f"""
        WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
        parts AS (SELECT doc_id, {WORDS} AS w, {LINES} AS l, len(regexp_extract_all(t, '[#*$%&|<>]')) AS n_symbols FROM d),
        windows AS (SELECT doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM parts WHERE len(w) >= 3) x),
        twice AS (SELECT doc_id, g FROM windows GROUP BY doc_id, g HAVING count(*) > 1),
        marked AS (SELECT DISTINCT doc_id, unnest([i, i + 1, i + 2]) AS i FROM windows JOIN twice USING (doc_id, g)),
        again AS (SELECT doc_id, count(*) AS n FROM marked GROUP BY doc_id)
        SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols,
            CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, CAST(coalesce(n, 0) AS BIGINT) AS n_repeat_words, len(w) < 50 OR 100 * coalesce(n, 0) > 50 * len(w) AS base_failed
        FROM parts LEFT JOIN again USING (doc_id)""",
}
