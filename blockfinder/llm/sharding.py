"""Sharding by longest processing time: groups that must stay together, largest first, to the least-loaded shard.

Groups of one size are interchangeable, so the schedule runs over the histogram of group sizes: a heap of shard loads
takes the sizes in descending order. The number of distinct sizes is at most the square root of twice the total size,
however many groups there are, and they stream through the driver. Each group then finds its shard by its rank among the groups of its size.
"""

from __future__ import annotations

import heapq
import itertools
import uuid
from collections.abc import Iterable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_text, documents, durable, join_uneven, rank_within, shared_folder, written

SHARDS = 16
BUCKETS = 1024
AT_ONCE = 500_000  # runs of 28 bytes that the driver holds and that are broadcast; more go to a table


def longest_first(sizes: Iterable[tuple[int, int]], shards: int) -> Iterator[tuple[int, int, int, int]]:
    """Deal the groups of ``sizes`` (size, groups), which come by descending size; gives runs (size, first rank, groups, shard).

    Equal loads go to the lower shard. Once the loads are within one size of each other, whole rounds of equal
    groups leave them so; such rounds are dealt at once, in the order that the heap would take. Only the loads are held.
    """
    heap = [(0, k) for k in range(shards)]
    for size, left in sizes:
        given = [0] * shards
        while left:
            low, high = heap[0][0], max(heap)[0]
            rounds = left // shards if high - low <= size else 0
            if rounds > 1:
                heap = [(load + rounds * size, k) for load, k in heap]
                given = [n + rounds for n in given]
                left -= rounds * shards
                continue
            load, k = heapq.heappop(heap)
            heapq.heappush(heap, (load + size, k))
            given[k] += 1
            left -= 1
        rank = 0
        for k, n in enumerate(given):
            if n:
                yield size, rank, n, k
                rank += n


def run_table(counts: DataFrame, shards: int, at_once: int) -> DataFrame:
    """The runs for ``counts`` (__total, n): (__total, __first, __groups, shard).

    Sizes stream through the driver in descending order and runs leave it ``at_once`` at a time, so that it never holds
    more; up to ``at_once`` of them are broadcast where they are joined, more are a table in the shared folder.
    """
    spark, schema, folder = counts.sparkSession, "__total long, __first long, __groups long, shard int", None
    ordered = counts.orderBy(F.desc("__total")).toLocalIterator()
    runs = longest_first(((r["__total"], r["n"]) for r in ordered), shards)
    while True:
        part = list(itertools.islice(runs, at_once))
        if folder is None and len(part) < at_once:
            return F.broadcast(spark.createDataFrame(part, schema))
        if not part:
            return spark.read.schema(schema).parquet(folder)
        folder = folder or f"{shared_folder(spark)}/{uuid.uuid4().hex}"
        spark.createDataFrame(part, schema).write.mode("append").option("compression", "zstd").parquet(folder)


def shard(df: DataFrame, key: str, group: Column, size: Column, shards: int = SHARDS, extra: dict[str, Column] | None = None) -> DataFrame:
    """Deal the rows of ``df`` into ``shards``: (key, *extra, size, shard, slot).

    Rows with equal ``group`` (null is a group of its own) stay together, however many they are; ``size`` must be at
    least 1. slot numbers the rows of a shard from 0 without gaps. Empty input gives no rows; repeated rows get slots
    of their own.
    """
    narrow = durable(df.select(F.col(key), *[c.alias(n) for n, c in (extra or {}).items()], size.cast("long").alias("size"), group.alias("__group")))
    groups = durable(narrow.groupBy("__group").agg(F.sum("size").alias("__total"), F.count(F.lit(1)).alias("__n")))
    counts = durable(groups.groupBy("__total").agg(F.count(F.lit(1)).alias("n")))
    ranked = rank_within(groups, ["__total"], ["__group"], "__rank", BUCKETS)
    home = ranked.join(run_table(counts, shards, AT_ONCE), "__total").where("__rank >= __first and __rank < __first + __groups").select("__group", "__n", "shard")
    dealt = join_uneven(narrow, written(home), "__group", "__n", narrow.count()).drop("__group")
    return rank_within(dealt, ["shard"], [key, *(extra or {}), "size"], "slot", BUCKETS)


def text_group(text: Column) -> Column:
    """Equal for equal texts only: 256 bits of a hash; null for null."""
    return F.unhex(F.sha2(text, 256))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    text = F.col("text")
    size = F.coalesce(F.octet_length(text), F.lit(0)) + 1
    out = shard(documents(spark, sf_dir), "doc_id", text_group(text), size, SHARDS, {"text_crc32": crc_text(text)})
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
