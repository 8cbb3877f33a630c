"""From a graph to blocks, in three timed stages."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from ..operators import features, gnn, selection
from ..operators.graph import Graph
from .state import settle, swept, written



def layers_for(n: int) -> tuple[int, ...]:
    """Layer sizes for a graph of ``n`` nodes.

    Each pass over the neighbours shrinks the noise against the communities, of which there is the more the more nodes
    there are to a block; a layer as wide as the one before, with orthonormal weights, keeps what is told apart.
    """
    return (256,) * 6 if n <= 30_000 else (384,) * 8



@dataclass(frozen=True)
class Result:
    blocks: DataFrame
    tree: DataFrame
    features: DataFrame
    embedding: DataFrame
    timings: dict[str, float] = field(default_factory=dict)


def partition(g: Graph, kind: str = "cut", layers: tuple[int, ...] | None = None, seed: int = 0, ablation: str | None = None, act: str = "tanh", weights: str = "orthogonal", normalise: bool = True, scale: str = "std", how: str = "auto", **select) -> Result:
    """Blocks of ``g``, by the cut or the modularity variant (``kind``).

    ``ablation``: ``no_features`` puts the structure matrix itself into the first layer; ``no_embedding`` bisects the
    features. ``layers``: by default ``layers_for``; ``weights``: the law of the layers' weights. Other arguments go to the
    model selection.
    """
    layers = layers or layers_for(g.n)
    began = time.perf_counter()
    skip = ablation == "no_features"
    y = written(features.project_through(g, kind, layers[1], seed) if skip else features.project(g, kind, layers[0], seed, scale))
    swept(g.nodes.sparkSession)
    drawn = time.perf_counter()
    z = y if ablation == "no_embedding" else gnn.forward(g, y, layers, seed, act, weights, normalise, not skip, how)
    z = z if len(layers) > 1 else settle(z)
    embedded = time.perf_counter()
    blocks, tree = selection.hierarchical(g, z, seed=seed, **select)
    done = time.perf_counter()
    return Result(blocks, tree, y, z, {"features": drawn - began, "embedding": embedded - drawn, "selection": done - embedded, "total": done - began})
