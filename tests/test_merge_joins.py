"""Plans as they are where no side of a join is small."""

import pytest
from pyspark.sql import functions as F

from blockfinder.operators import baselines, generator, graph, metrics


@pytest.fixture
def merged(spark):
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield spark
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)


def test_spectral_clustering_over_merge_joins(merged):
    nodes = merged.range(2000).select(F.col("id"), (F.col("id") % 4).cast("int").alias("b"))
    p = generator.benchmark_params(nodes, mean_degree=20.0, block="b")
    g = graph.build(generator.sample(p, "skip", 0), nodes, "src", "dst")
    assert metrics.scores(p.nodes, baselines.spectral_clustering(g, 4))["ari"] > 0.5
