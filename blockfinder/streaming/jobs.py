"""Jobs on Structured Streaming: edges from files, running degrees, late rows, and batches that update the blocks."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.state import shared_folder

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_edges(spark: SparkSession, path: str, files_a_batch: int = 1) -> DataFrame:
    """A stream of (a, b, event_time, event_id, event_type) from a folder or file of events."""
    return as_edges(spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_a_batch).option("pathGlobFilter", "events*.parquet").parquet(path))


def event_edges_batch(spark: SparkSession, sf: str) -> DataFrame:
    """The same rows, as a table."""
    return as_edges(spark.read.parquet(f"{sf}/events.parquet"))


def as_edges(rows: DataFrame) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("long")
    return rows.select(F.col("user_id").alias("a"), (k + 1_000_000_000).alias("b"), F.col("ts").cast("timestamp").alias("event_time"), "event_id", "event_type").where("b is not null")


def run(stream: DataFrame, mode: str, spark: SparkSession) -> DataFrame:
    """Run over what there is and give the rows of the sink, tables in the shared folder: no rows come to the driver.

    A complete result replaces the one before the last; a batch that is given again is written to the same place.
    """
    name = f"sink_{uuid.uuid4().hex}"
    folders: dict[str, None] = {}

    def keep(rows: DataFrame, k: int) -> None:
        folder = f"{shared_folder(spark)}/{name}_rows/{k % 2 if mode == 'complete' else k}"
        rows.write.mode("overwrite").parquet(folder)
        if mode == "complete":
            folders.clear()
        folders[folder] = None

    stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{shared_folder(spark)}/{name}").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(*folders) if folders else spark.createDataFrame([], stream.schema)


def without_repeats(edges: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Edges once each within the watermark; later repeats are dropped by the state's limits."""
    return edges.withWatermark("event_time", delay).dropDuplicatesWithinWatermark(["a", "b"])


def windowed(edges: DataFrame, kind: str, delay: str = "1 day") -> DataFrame:
    """Events of each user in tumbling, sliding or session windows."""
    marked = edges.withWatermark("event_time", delay)
    span = {"tumbling": F.window("event_time", "1 day"), "sliding": F.window("event_time", "1 day", "12 hours"), "session": F.session_window("event_time", "6 hours")}[kind]
    return marked.groupBy("a", span.alias("w")).agg(F.count(F.lit(1)).alias("n")).select("a", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def with_blocks(edges: DataFrame, blocks: DataFrame) -> DataFrame:
    """Each arriving edge with the current block of its first end; ``blocks`` is a table."""
    return edges.join(blocks.select(F.col("id").alias("a"), "block"), "a", "left")


def click_then_purchase(edges: DataFrame) -> DataFrame:
    """Pairs of a user's click and a purchase within the next hour, as a join of two streams."""
    click = edges.where("event_type = 'click'").select(F.col("a").alias("user"), F.col("event_id").alias("click_id"), F.col("event_time").alias("t0")).withWatermark("t0", "2 hours")
    bought = edges.where("event_type = 'purchase'").select(F.col("a").alias("buyer"), F.col("event_id").alias("purchase_id"), F.col("event_time").alias("t1")).withWatermark("t1", "2 hours")
    return click.join(bought, F.expr("user = buyer AND t1 > t0 AND t1 <= t0 + INTERVAL 1 HOUR")).select("user", "click_id", "purchase_id")


def stateful_degrees(edges: DataFrame) -> DataFrame:
    """(id, deg) after each batch, counts of events held in the state store for each node."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def count(key, frames, state):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"id": [key[0]], "deg": [n]})

    return edges.groupBy("a").applyInPandasWithState(count, "id long, deg long", "deg long", "update", GroupStateTimeout.NoTimeout)


def each_batch(edges: DataFrame, apply: Callable[[DataFrame, int], None], spark: SparkSession) -> None:
    """Hand each micro-batch of edges (a, b) to ``apply``; a batch that is given again must change nothing."""
    place = f"{shared_folder(spark)}/{uuid.uuid4().hex}"
    edges.select("a", "b").writeStream.foreachBatch(lambda rows, k: apply(rows, k)).option("checkpointLocation", place).trigger(availableNow=True).start().awaitTermination()
