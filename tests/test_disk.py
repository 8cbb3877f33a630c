"""Larger graphs: what a run moves and leaves on disk."""

from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockfinder import queries
from blockfinder.operators import generator, gnn, graph
from blockfinder.plans import experiments
from blockfinder.plans.pipeline import partition
from blockfinder.plans.state import shared_folder, written

queries.load_all()


@pytest.fixture(scope="module")
def ring(spark):
    nodes = spark.range(3000).select(F.col("id"), (F.col("id") % 4).cast("int").alias("b"))
    p = generator.benchmark_params(nodes, ratio=6.0, mean_degree=20.0, block="b")
    return graph.build(generator.sample(p, "skip", 1), nodes, "src", "dst")


def vectors_of(z):
    return np.array([r["v"] for r in z.orderBy("id").collect()])


def folders(spark):
    where = Path(shared_folder(spark).removeprefix("file:"))
    return {x.name for x in where.iterdir() if not x.name.startswith("rdd-")}


def test_layers_through_files_move_no_vectors(spark, ring, monkeypatch):
    monkeypatch.setattr(gnn, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(gnn, "BLOCK_BYTES", 1 << 18)
    y = written(ring.nodes.select("id", F.transform(F.sequence(F.lit(0), F.lit(31)), lambda k: F.sin(F.col("id") * (k + 1))).cast("array<float>").alias("v")))
    layers = (32,) * 5
    assert gnn.plan_for(ring.n, 32, 20.0) == "blocks"
    want = vectors_of(gnn.forward(ring, y, layers, how="broadcast"))
    before = folders(spark)
    out = []
    cost = experiments.plan_cost(spark, lambda: out.append(gnn.forward(ring, y, layers)))
    # The join with the nodes, the first vectors and the arcs are dealt out once; layers shuffle nothing.
    assert cost["shuffle_bytes"] < 3 * 4 * 32 * ring.n + 24 * (2 * ring.m + ring.n)
    assert len(folders(spark) - before) == 1
    assert np.abs(vectors_of(out[0]) - want).max() < 1e-4


def test_levels_leave_no_vectors_behind(spark, ring):
    before = folders(spark)
    r = partition(ring, "cut", (32,) * 4, local_below=200)
    again = partition(ring, "cut", (32,) * 4)
    assert {tuple(x) for x in r.blocks.select("id", "block").collect()} == {tuple(x) for x in again.blocks.select("id", "block").collect()}
    wide = [x for x in folders(spark) - before if "v" in spark.read.parquet(f"{shared_folder(spark)}/{x}").columns]
    assert len(wide) == 2 * 2  # features and embedding of both runs


def test_dense_matrix_is_not_shuffled(spark, tmp_path):
    orders = spark.range(400)
    lines = orders.select(F.col("id").alias("l_orderkey"), (F.col("id") % 300).alias("l_suppkey")).unionByName(orders.select(F.col("id").alias("l_orderkey"), ((F.col("id") * 7 + 1) % 300).alias("l_suppkey")))
    lines.write.parquet(f"{tmp_path}/lineitem.parquet")
    out = []
    cost = experiments.plan_cost(spark, lambda: out.extend(queries.QUERIES["weights_mod_full_rankone"](spark, str(tmp_path)).collect()))
    assert cost["shuffle_rows"] < 30_000
    edges = {(min(a, b), max(a, b)) for a, b in ((k % 300, (k * 7 + 1) % 300) for k in range(400)) if a != b}
    deg = np.bincount([x for e in edges for x in e], minlength=300)
    ids = np.flatnonzero(deg)
    assert len(out) == len(ids) ** 2
    for r in out:
        linked = (min(r["src"], r["dst"]), max(r["src"], r["dst"])) in edges
        assert abs(r["q"] - (linked - deg[r["src"]] * deg[r["dst"]] / (2 * len(edges)))) < 1e-6


def test_ends_are_found_without_the_driver(spark):
    nodes = spark.range(300).select(F.col("id"), (F.col("id") % 3).cast("int").alias("b"))
    plan = generator.split(generator.benchmark_params(nodes, mean_degree=10.0, block="b"))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("SortMergeJoin") >= 2


def test_split_draws_one_node_for_each_end(spark):
    p = generator.benchmark_params(spark.range(600), mean_degree=10.0, k=3)
    drawn = generator.split(p, 1).agg(F.sum("weight")).first()[0]
    mass = generator.rates_df(p).agg(F.sum("mass")).first()[0]
    assert abs(drawn - mass) < 6 * mass**0.5  # a Poisson total


def test_strips_from_files_are_the_same(spark, monkeypatch):
    p = generator.benchmark_params(spark.range(900), mean_degree=8.0, k=5)
    monkeypatch.setattr(generator, "GROUP_NODES", 300)
    monkeypatch.setattr(generator, "STRIPS_AT_ONCE", 2)
    monkeypatch.setattr(generator, "block_arrays", None)  # nodes are not joined to strips
    rows = [sorted(map(tuple, generator.skip(p, 3, strip_edges=100, broadcast_nodes=n).collect())) for n in (900, 899)]
    assert rows[0] == rows[1] and len(rows[0]) > 3000
