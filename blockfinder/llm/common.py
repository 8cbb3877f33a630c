"""Helpers that the operators of this folder share."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.state import shared_folder, written

__all__ = ["shared_folder", "written"]

SLICE_BYTES = 16 << 20
HOT = 4096  # a key with over one in so many rows is popular
LOWER = np.array([c + 32 if 0x41 <= c <= 0x5A else c for c in range(256)], np.uint8)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def making_room(df: DataFrame, added: list[str]) -> DataFrame:
    """``df`` without columns whose names are to be added: what is new takes their place."""
    return df.drop(*[c for c in added if c in df.columns])


def durable(df: DataFrame) -> DataFrame:
    """Cut the lineage of ``df`` with a reliable checkpoint in the folder that the cluster shares.

    The folder is the session's ``spark.checkpoint.dir``; only where that is unset and Spark is local, one is made.
    """
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def arrow_map(df: DataFrame, rows: Callable[[Iterator[pa.RecordBatch]], Iterable[pa.RecordBatch]], schema: str, slice_bytes: int = SLICE_BYTES) -> DataFrame:
    """mapInArrow that skips empty batches and hands on large ones in slices of about slice_bytes."""

    def sliced(batches):
        for b in batches:
            step = max(1, b.num_rows * slice_bytes // max(b.nbytes, slice_bytes))
            for at in range(0, b.num_rows, step):
                yield b.slice(at, step)

    def run(batches):
        yield from rows(sliced(batches))
        pa.default_memory_pool().release_unused()

    return df.mapInArrow(run, schema)


def as_bytes(column: pa.Array) -> pa.Array:
    """A text column as UTF-8 bytes, null as empty."""
    return pc.fill_null(column.cast(pa.large_binary()), b"")


def ascii_words(column: pa.Array, lower: bool) -> tuple[np.ndarray, pa.Array]:
    """Words ``[^\\x20\\x09-\\x0D]+`` of every text (null: none), with A-Z lower-cased on request.

    Gives the number of words of each text and all words, one after the other.
    """
    text = pc.fill_null(column.cast(pa.large_string()), "")
    if lower and len(text):
        offsets = np.frombuffer(text.buffers()[1], "i8")[text.offset : text.offset + len(text) + 1]
        data = LOWER[np.frombuffer(text.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]]]
        text = pa.LargeStringArray.from_buffers(len(text), pa.py_buffer(offsets - offsets[0]), pa.py_buffer(data))
    parts = pc.ascii_split_whitespace(text)
    words = parts.flatten()
    counts = np.diff(parts.offsets.to_numpy())
    full = pc.not_equal(pc.binary_length(words), 0)
    if not pc.all(full).as_py():
        doc = np.repeat(np.arange(len(text)), counts)[full.to_numpy(zero_copy_only=False)]
        counts = np.bincount(doc, minlength=len(text))
        words = words.filter(full)
    return counts, words


def rank_within(df: DataFrame, group: list[str], order: list[str], out: str, buckets: int = 1024) -> DataFrame:
    """Number the rows of each group from 0 without gaps, however large a group is.

    Rows are dealt into ``buckets`` cells of their group by a hash of ``order``; each cell is numbered by itself and
    starts where the cells before it end. A group is never gathered in one task; the prefix sums see at most
    ``buckets`` rows for each group. Rows that agree in all of ``order`` are interchangeable.
    """
    cell, size, start = "__cell", "__cell_size", "__cell_start"
    dealt = df.withColumn(cell, F.pmod(F.xxhash64(*order), F.lit(buckets)).cast("int"))
    before = Window.partitionBy(*group).orderBy(cell).rowsBetween(Window.unboundedPreceding, -1)
    starts = dealt.groupBy(*group, cell).agg(F.count(F.lit(1)).alias(size)).select(*group, cell, F.coalesce(F.sum(size).over(before), F.lit(0)).alias(start))
    numbered = dealt.withColumn(out, F.row_number().over(Window.partitionBy(*group, cell).orderBy(*order)) - 1)
    joined = numbered.alias("n").join(starts.alias("s"), on=[F.col(f"n.{c}").eqNullSafe(F.col(f"s.{c}")) for c in (*group, cell)])
    return joined.select(*[F.col(f"n.{c}") for c in df.columns], (F.col(f"n.{out}") + F.col(f"s.{start}")).cast("long").alias(out))


def join_uneven(rows: DataFrame, home: DataFrame, key: str, n: str, total: int) -> DataFrame:
    """``rows`` joined with ``home``, which has one row a key (null too) and, in its column ``n``, how many of ``total`` rows the key has.

    Keys with over one in ``HOT`` rows, fewer than ``HOT`` of them by that, are broadcast and their rows stay where they
    are; only the others are shuffled. So no task gets all rows of a popular key. ``home`` should be cheap to read twice.
    """
    on = F.col(f"r.{key}").eqNullSafe(F.col(f"h.{key}"))
    added = [F.col(f"h.{c}") for c in home.columns if c not in (key, n)]
    hot = home.where(F.col(n) * HOT > total)
    if hot.isEmpty():
        return rows.alias("r").join(home.alias("h"), on).select("r.*", *added)
    often = rows.alias("r").join(F.broadcast(hot).alias("h"), on).select("r.*", *added)
    others = rows.alias("r").join(F.broadcast(hot.select(key)).alias("h"), on, "left_anti")
    return often.unionByName(others.alias("r").join(home.where(F.col(n) * HOT <= total).alias("h"), on).select("r.*", *added))


def free_name(df: DataFrame, name: str) -> str:
    """``name``, made longer until ``df`` has no such column."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def crc_text(column: Column) -> Column:
    """CRC-32 of a value as text, unsigned; null counts as empty."""
    return F.crc32(F.coalesce(column.cast("string"), F.lit("")))


def frequent(counts: DataFrame, word: str, n: str, most: int, most_bytes: int) -> Column | None:
    """A condition that the most frequent words meet, at most ``most`` of them and none longer than ``most_bytes``.

    A histogram over the logarithm of the frequency, which is small, gives the least one. None if even the words of the
    highest level are too many.
    """
    level = F.floor(F.log2(n) * 16).cast("int")
    short = F.octet_length(word) <= most_bytes
    levels = sorted(((r["level"], r["count"]) for r in counts.where(short).groupBy(level.alias("level")).count().collect()), reverse=True)
    room, least = most, None
    for k, size in levels:
        if size > room:
            break
        room, least = room - size, k
    return None if least is None else short & (level >= least)
