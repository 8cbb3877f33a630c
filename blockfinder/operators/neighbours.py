"""Exact nearest neighbours of given vectors, block against block."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK_ROWS = 8_192


def nearest(z: DataFrame, k: int, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(a, b, far): the ``k`` nearest others of each row of ``z`` (id, v), by squared distance and then id.

    Every block of rows meets every block; a meeting gives the k best of each row there, and the best of all meetings
    stay. No task holds more than two blocks, and what is moved grows with rows times blocks, not with pairs of rows.
    """
    blocks = max(1, -(-z.count() // block_rows))
    block = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    rows = z.where("id is not null and v is not null").select("id", F.col("v").cast("array<double>").alias("v"))
    left, right = rows.select(block.alias("i"), every.alias("j"), "id", "v"), rows.select(every.alias("i"), block.alias("j"), "id", "v")

    def meet(one, two):
        out = {"a": [], "b": [], "far": []}
        if one.num_rows and two.num_rows:
            ids, others = one["id"].to_numpy(), two["id"].to_numpy()
            x, y = (t["v"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(t.num_rows, -1) for t in (one, two))
            for at in range(0, len(ids), 512):
                part = x[at : at + 512]
                far = np.stack([((y - row) ** 2).sum(axis=1) for row in part]) if len(y) * len(part) < 1 << 12 else distances(part, y)
                far[ids[at : at + 512, None] == others[None, :]] = np.inf
                best = np.lexsort((np.broadcast_to(others, far.shape), far), axis=1)[:, :k]
                row = np.repeat(np.arange(len(part)), best.shape[1])
                place = best.reshape(-1)
                there = np.isfinite(far[row, place])
                out["a"].append(ids[at + row[there]]), out["b"].append(others[place[there]]), out["far"].append(far[row[there], place[there]])
        kinds = {"a": pa.int64(), "b": pa.int64(), "far": pa.float64()}
        return pa.table({c: pa.array(np.concatenate(x) if x else np.zeros(0), kinds[c]) for c, x in out.items()})

    met = left.groupBy("i", "j").cogroup(right.groupBy("i", "j")).applyInArrow(meet, "a long, b long, far double")
    best = F.slice(F.array_sort(F.collect_list(F.struct("far", "b"))), 1, k)  # k rows from each block
    return met.groupBy("a").agg(best.alias("x")).select("a", F.explode("x").alias("x")).select("a", "x.b", "x.far")


def distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Squared distances, summed column by column so that each is the same wherever its rows are."""
    out = np.zeros((len(x), len(y)))
    for c in range(x.shape[1]):
        out += (x[:, c, None] - y[None, :, c]) ** 2
    return out
