"""The complete graph over given nodes: its arcs are sums over all nodes and are never listed."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.state import settle, written
from . import bisect, features, gnn, selection
from .graph import Graph
from .kernels import vectors


def graph_of(nodes: DataFrame) -> Graph:
    """Nodes (id) with their degree; the arcs are left out."""
    own = settle(nodes.select(F.col("id").cast("long").alias("id")).where("id is not null").distinct())
    n = own.count()
    empty = own.sparkSession.createDataFrame([], "src long, dst long, dsrc long, ddst long")
    return Graph(own.withColumn("deg", F.lit(n - 1).cast("long")), empty, n, n * (n - 1) // 2)


def embed(g: Graph, layers: tuple[int, ...], seed: int = 0, act: str = "tanh") -> DataFrame:
    """(id, deg, v): ``gnn.forward`` of the cut variant's ``features.project``.

    A node's features are all Gaussian rows but its own, over the degree. A layer sums over the neighbours and the node
    itself, which are all nodes, so that from the first one on all rows are the same.
    """
    if len(layers) < 2:
        raise ValueError("at least one layer after the features")
    whole = features.weighted_sum(g, layers[0], seed) / max(1, g.n - 1)  # degrees are equal
    row = whole * features.spread(layers[0], "std") / max(1, g.n)
    for k in range(len(layers) - 1):
        row = gnn.unit_rows(gnn.ACTIVATIONS[act]((row @ gnn.weights(layers[k], layers[k + 1], seed, k))[None, :]))[0]

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), vectors(np.tile(row, (b.num_rows, 1)))], ["id", "deg", "v"])

    return g.nodes.select("id", "deg").mapInArrow(run, "id long, deg long, v array<float>")


def partition(nodes: DataFrame, layers: tuple[int, ...], seed: int = 0, eps: int = 5) -> DataFrame:
    """(id, block) as ``plans.pipeline.partition`` gives for the listed graph by the cut variant.

    Two-means is asked once: halves of a and b nodes have a * b edges between them, and a b n (n - 1) is over
    a b (n - 1) ** 2, so that no division of a complete graph stays, whatever the embedding.
    """
    g = graph_of(nodes)
    assign = written(embed(g, layers, seed).withColumn("path", F.lit("")))
    if g.n:
        planes = bisect.two_means(assign, {"": g.n}, seed=seed)
        b = bisect.assign_side(assign, planes).agg(F.sum("side")).first()[0]
        a = g.n - b
        if selection.stays(a, b, a * (g.n - 1), b * (g.n - 1), a * b, a * (a - 1) // 2, b * (b - 1) // 2, 2 * g.m, eps, "graph"):
            raise AssertionError("a division of a complete graph stays")
    return selection.label(assign.select("id", "path")).select("id", "block")
