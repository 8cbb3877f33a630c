"""Sparse-dense products over arcs, in Arrow batches.

Arcs come clustered and sorted by ``src``; a node's sum is carried from batch to batch, so memory does not grow with its
degree. Vectors are float32 arrays.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ROWS_AT_ONCE = 3 << 19  # bytes of vectors that are summed in one go: what a core's cache holds
IDS_AT_ONCE = 1 << 11
HUB_ARCS = 1 << 22  # most arcs of one node in a task


def matrix(column: pa.Array, width: int) -> np.ndarray:
    """A list column without nulls as rows of a float32 matrix."""
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), width).astype("f4", copy=False)


def vectors(rows: np.ndarray) -> pa.Array:
    rows = np.ascontiguousarray(rows, "f4")
    return pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1, dtype="i4") * rows.shape[1]), pa.array(rows.reshape(-1)))


def arcs_at_once(width: int) -> int:
    return max(64, ROWS_AT_ONCE // (4 * width))


def summed_by(batches: Iterable[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Sums of the rows of each id, with the id's tag, for (ids, tags, rows) that come sorted, ``IDS_AT_ONCE`` or so at a time.

    Rows of one batch are added up as they are; the last id waits for the next batch, in double precision.
    """
    held: tuple[int, int, np.ndarray] | None = None
    full: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    for ids, tags, rows in batches:
        if not len(ids):
            continue
        starts = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
        sums, own, tag = np.add.reduceat(rows, starts, axis=0), ids[starts], tags[starts]
        last = sums[-1].astype("f8")
        if held is not None:
            if held[0] != own[0]:
                full.append((np.array([held[0]]), np.array([held[1]]), held[2][None]))
            elif len(own) == 1:
                last += held[2]
            else:
                sums[0] = held[2] + sums[0]
        held = (int(own[-1]), int(tag[-1]), last)
        if len(own) > 1:
            full.append((own[:-1], tag[:-1], sums[:-1]))
        if sum(len(x[0]) for x in full) >= IDS_AT_ONCE:
            yield tuple(np.concatenate(x) for x in zip(*full, strict=True))
            full = []
    if held is not None:
        full.append((np.array([held[0]]), np.array([held[1]]), held[2][None]))
        yield tuple(np.concatenate(x) for x in zip(*full, strict=True))


def hub_salt(g) -> int:
    """Into how many parts the arcs of a node are dealt, so that no task has over ``HUB_ARCS`` of one node's."""
    most = g.nodes.agg(F.max("deg")).first()[0] or 0
    return max(1, -(-most // HUB_ARCS))


def by_source(arcs: DataFrame, columns: list[str], salt: int = 1) -> DataFrame:
    """Arcs of one ``src`` in one partition, in order. With ``salt``, a node's arcs are spread over so many."""
    narrow = arcs.select("src", *columns)
    if salt > 1:
        return narrow.repartition("src", F.pmod(F.xxhash64("dst"), F.lit(salt))).sortWithinPartitions("src")
    return narrow.repartition("src").sortWithinPartitions("src")


def reduce_arcs(arcs: DataFrame, columns: list[str], width: int, rows: Callable[..., np.ndarray], salt: int = 1) -> DataFrame:
    """(id, v): the sum over each node's arcs of ``rows(*columns)``, a matrix with a row for each arc."""

    def run(batches: Iterable[pa.RecordBatch]):
        def parts():
            step = arcs_at_once(width)
            for batch in batches:
                at = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
                for k in range(0, batch.num_rows, step):
                    part = [c[k : k + step] for c in at]
                    yield part[0], part[0], rows(*part[1:])

        for ids, _, sums in summed_by(parts()):
            yield pa.RecordBatch.from_arrays([pa.array(ids), vectors(sums)], ["id", "v"])

    out = by_source(arcs, columns, salt).mapInArrow(run, "id long, v array<float>")
    return sum_vectors(out, width) if salt > 1 else out


def sum_vectors(df: DataFrame, width: int) -> DataFrame:
    """(id, v) summed by id."""

    def run(batches: Iterable[pa.RecordBatch]):
        for ids, _, sums in summed_by((b.column(0).to_numpy(), b.column(0).to_numpy(), matrix(b.column(1), width)) for b in batches if b.num_rows):
            yield pa.RecordBatch.from_arrays([pa.array(ids), vectors(sums)], ["id", "v"])

    return df.select("id", "v").repartition("id").sortWithinPartitions("id").mapInArrow(run, "id long, v array<float>")
