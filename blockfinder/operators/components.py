"""Connected components of an edge table, by contraction."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.state import written

#: What is left of the edges is finished in one task from this many on; the result is the same.
ONE_TASK = 200_000


def components(edges: DataFrame, one_task: int = ONE_TASK) -> DataFrame:
    """(node, root) of every node of ``edges`` (a, b; longs): root is the least node of its component.

    Each round hangs every node on its least neighbour and follows these steps up until they end, so that a chain in
    order is one round; then it joins what is left of the edges between the new ends. A node that nothing hangs on
    hangs itself in the next round, so that two rounds at least halve the nodes, and there is no limit of rounds.
    Nodes with many edges are only ever aggregated or joined, never gathered. Loops and edges with a null are ignored.
    """
    found = None
    edges = written(contracted(edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b"))))
    while (left := edges.count()) > 0:
        up = written(joined_in_one_task(edges)) if left <= one_task else followed(least_neighbours(edges))
        if found is None:
            found = up.select("node", F.col("up").alias("root"))
        else:
            found = written(found.join(up.select(F.col("node").alias("root"), "up"), "root", "left").select("node", F.coalesce("up", "root").alias("root")))
        if left <= one_task:
            break
        one, two = up.select(F.col("node").alias("a"), F.col("up").alias("x")), up.select(F.col("node").alias("b"), F.col("up").alias("y"))
        edges = written(contracted(edges.join(one, "a").join(two, "b").select(F.col("x").alias("a"), F.col("y").alias("b"))))
    return edges.select(F.col("a").alias("node"), F.col("b").alias("root")) if found is None else found


def contracted(edges: DataFrame) -> DataFrame:
    return edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def least_neighbours(edges: DataFrame) -> DataFrame:
    """(node, up): the least of a node and its neighbours."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    return both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("b")).select("node", F.least("node", "b").alias("up"))


def followed(up: DataFrame) -> DataFrame:
    """(node, up) with each step replaced by the end of its path. Steps lead downwards, so paths end."""
    up = written(up)
    while True:
        top = up.select(F.col("node").alias("up"), F.col("up").alias("top"))
        further = written(up.join(top, "up").select("node", F.col("top").alias("up"), (F.col("top") < F.col("up")).alias("moved")))
        up = further.select("node", "up")
        if further.where("moved").isEmpty():
            return up


def joined_in_one_task(edges: DataFrame) -> DataFrame:
    """(node, up) for edges that one task can hold."""

    def run(batches):
        parts = [np.stack([c.to_numpy() for c in b.columns]) for b in batches if b.num_rows]
        if parts:
            a, b = np.concatenate(parts, axis=1)
            nodes, place = np.unique(np.r_[a, b], return_inverse=True)
            roots = joined(len(nodes), place[: len(a)], place[len(a) :])
            yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(nodes[roots])], ["node", "up"])

    return edges.coalesce(1).mapInArrow(run, "node long, up long")


def joined(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least place of the component of each of n places, with edges between the places a and b."""
    labels = np.arange(n)
    while True:
        x, y = labels[a], labels[b]
        apart = x != y
        if not apart.any():
            return labels
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(labels, np.maximum(x, y), np.minimum(x, y))
        while True:
            further = labels[labels]
            if (further == labels).all():
                break
            labels = further
