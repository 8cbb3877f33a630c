"""A batch data source that draws a block-model graph: ``spark.read.format("planted")``.

Options: nodes, blocks (0: the floor of nodes ** 0.35), ratio, mean_degree, heterogeneity, seed, strips. Each partition
draws the rows of one strip of one block pair; a retried partition draws the same edges.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.rng import uniform_block
from ..operators.generator import STRIP_EDGES, THETA_HIGH, THETA_LOW, THETA_POWER, block_shares, draw_strip, solve_rates, theta_mean


class Strip(InputPartition):
    def __init__(self, r: int, s: int, rate: float, first: int, last: int):
        super().__init__((r, s, rate, first, last))


class PlantedReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.nodes = int(options.get("nodes", 1000))
        self.blocks = int(options.get("blocks", 0)) or max(1, math.floor(self.nodes**0.35))
        self.ratio, self.degree = float(options.get("ratio", 2.5)), float(options.get("mean_degree", 36))
        self.heterogeneity, self.seed = float(options.get("heterogeneity", 3)), int(options.get("seed", 0))

    def members(self) -> tuple[np.ndarray, np.ndarray]:
        ids = np.arange(self.nodes)
        u = uniform_block(self.seed, ids, 2)
        block = np.searchsorted(np.cumsum(block_shares(self.blocks, self.heterogeneity, self.seed))[:-1], u[:, 0], "right")
        a, b = THETA_LOW ** (1 - THETA_POWER), THETA_HIGH ** (1 - THETA_POWER)
        return block, (a + u[:, 1] * (b - a)) ** (1 / (1 - THETA_POWER)) / theta_mean()

    def partitions(self):
        block, theta = self.members()
        sums = [(k, int((block == k).sum()), float(theta[block == k].sum()), float((theta[block == k] ** 2).sum())) for k in range(self.blocks) if (block == k).any()]
        size = {k: (n, t) for k, n, t, _ in sums}
        out = []
        for r, s, rate in solve_rates(sums, self.ratio, self.degree, True, True):
            n = size[r][0]
            strips = max(1, min(n, math.ceil(rate * size[r][1] * size[s][1] / STRIP_EDGES)))
            out += [Strip(r, s, rate, n * k // strips, n * (k + 1) // strips) for k in range(strips)]
        return out

    def read(self, partition):
        r, s, rate, first, last = partition.value
        block, theta = self.members()
        a, b = np.flatnonzero(block == r), np.flatnonzero(block == s)
        src, dst, weight = draw_strip(a, theta[a], b, theta[b], rate, first, last, r == s, np.random.default_rng([self.seed, r, s, first]))
        yield from zip(np.minimum(src, dst).tolist(), np.maximum(src, dst).tolist(), weight.tolist(), strict=True)


class PlantedSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return "src long, dst long, weight long"

    def reader(self, schema) -> PlantedReader:
        return PlantedReader(dict(self.options))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PlantedSource)
