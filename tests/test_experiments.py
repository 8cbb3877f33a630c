"""Components on chains, the generator's two forms, nearest neighbours, limits, and registered queries against SQL."""

import itertools
import time
from pathlib import Path

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from blockfinder import queries
from blockfinder.operators import components, generator, gnn, graph, neighbours
from blockfinder.operators.kernels import matrix, summed_by
from blockfinder.plans import experiments

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("one_task", [0, 1_000_000])
def test_components_of_chains_stars_and_rings(spark, one_task):
    order = [*range(3000), *(3000 + np.random.default_rng(2).permutation(2000)).tolist()]
    edges = [*itertools.pairwise(order), *[(9000, 9001 + k) for k in range(50)], *[(7000 + k, 7000 + (k + 1) % 20) for k in range(20)], (5, 5), (None, 4)]
    found = {r["node"]: r["root"] for r in components.components(spark.createDataFrame(edges, "a long, b long"), one_task).collect()}
    assert {found[k] for k in order} == {0}
    assert {found[9000 + k] for k in range(51)} == {9000} and {found[7000 + k] for k in range(20)} == {7000}
    assert len(found) == 5000 + 51 + 20
    assert not components.components(spark.createDataFrame([(1, 1)], "a long, b long"), one_task).collect()


def test_strips_are_the_same_however_blocks_reach_them(spark):
    params = generator.benchmark_params(spark.range(300), k=4, mean_degree=10.0)
    one, two = (sorted(map(tuple, generator.skip(params, 5, 200, broadcast_nodes=n).collect())) for n in (0, 10_000))
    assert one == two and len(one) > 500


def test_even_blocks_keep_the_ratio_in_each_block(spark):
    nodes = spark.range(900).withColumn("b", F.when(F.col("id") < 150, 0).when(F.col("id") < 500, 1).otherwise(2))
    for even, same in (("blocks", True), ("totals", False)):
        p = generator.benchmark_params(nodes, mean_degree=20.0, block="b", simple=False, even=even)
        mass = {(r["r"], r["s"]): r["mass"] for r in generator.rates_df(p).collect()}
        assert sum(mass.values()) == pytest.approx(9000)
        ratio = [mass[k, k] / (sum(mass[min(k, j), max(k, j)] for j in range(3) if j != k) / 2) for k in range(3)]
        assert (max(ratio) / min(ratio) < 2.2) == same


def test_orthogonal_weights_keep_distances():
    for rows, columns in ((8, 8), (8, 5), (5, 8)):
        w = gnn.weights(rows, columns, 3, 1)
        assert w.shape == (rows, columns)
        small = w.T @ w if rows >= columns else w @ w.T
        assert small == pytest.approx(np.eye(min(rows, columns)), abs=1e-9)


def test_sums_over_batches():
    rng = np.random.default_rng(0)
    ids = np.sort(rng.integers(0, 30, 400))
    ids[100:300] = 12
    ids.sort()
    rows = rng.random((400, 3)).astype("f4")
    for step in (1, 7, 400):
        parts = list(summed_by((ids[k : k + step], ids[k : k + step] * 2, rows[k : k + step]) for k in range(0, 400, step)))
        got = {int(i): (int(t), r) for a, b, c in parts for i, t, r in zip(a, b, c, strict=True)}
        assert len(got) == sum(len(a) for a, _, _ in parts) == len(set(ids.tolist()))
        for i, (tag, total) in got.items():
            assert tag == 2 * i and total == pytest.approx(rows[ids == i].sum(axis=0), rel=1e-5)


def test_a_hub_is_dealt_out(spark, monkeypatch):
    star = [(0, k) for k in range(1, 120)] + [(k, k + 1) for k in range(1, 100)]
    g = graph.build(spark.createDataFrame(star, "a long, b long"))
    from blockfinder.operators import features, kernels

    whole = {r["id"]: r["v"] for r in features.project(g, "cut", 4, 1).collect()}
    y = features.project(g, "cut", 4, 1)
    z = {how: {r["id"]: r["v"] for r in gnn.forward(g, y, (4, 3), 1, how=how).collect()} for how in ("broadcast", "blocks", "join")}
    monkeypatch.setattr(kernels, "HUB_ARCS", 10)
    assert kernels.hub_salt(g) == 12
    dealt = {r["id"]: r["v"] for r in features.project(g, "cut", 4, 1).collect()}
    assert all(dealt[i] == pytest.approx(v, abs=1e-5) for i, v in whole.items())
    again = {r["id"]: r["v"] for r in gnn.forward(g, y, (4, 3), 1, how="broadcast").collect()}
    for rows in (*z.values(), again):
        assert all(rows[i] == pytest.approx(v, abs=1e-4) for i, v in z["join"].items())


@pytest.mark.parametrize("block_rows", [7, 1000])
def test_nearest_against_brute_force(spark, block_rows):
    rng = np.random.default_rng(4)
    z = rng.integers(0, 3, (40, 4)).astype(float)  # many ties
    rows = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(z)] + [(99, None)], "id long, v array<double>")
    found = {(r["a"], r["b"]) for r in neighbours.nearest(rows, 3, block_rows).collect()}
    for a in range(40):
        order = sorted((((z[a] - z[b]) ** 2).sum(), b) for b in range(40) if b != a)[:3]
        assert {b for x, b in found if x == a} == {b for _, b in order}


def test_a_run_is_cancelled_at_its_limit(spark):
    def slow():
        return spark.range(0, 8, 1, 8).mapInArrow(lambda batches: (time.sleep(30) or b for b in batches), "id long").count()

    status, out, took = experiments.limited(spark, slow, 2.0)
    assert (status, out, took) == ("OOT", None, 2.0)
    assert experiments.limited(spark, lambda: spark.range(5).count(), 60.0)[:2] == ("ok", 5)
    assert experiments.limited(spark, lambda: 1 / 0, 60.0)[0] == "failed"


def test_table_of_methods(spark):
    p = generator.benchmark_params(spark.range(300), ratio=5.0, mean_degree=20.0, k=3)
    g = graph.build(generator.sample(p, "skip", 0), spark.range(300), "src", "dst")

    def broken(g):
        raise MemoryError("too large")

    some = {"cut": lambda g: __import__("blockfinder.plans.pipeline", fromlist=["partition"]).partition(g, "cut", (64, 64, 64)), "broken": broken}
    made = experiments.quality_table(spark, [("tiny", 0, p.nodes, g)], some).persist()
    rows = {r["method"]: r for r in made.collect()}
    assert rows["cut"]["status"] == "ok" and rows["cut"]["acc"] > 0.95 and rows["broken"]["status"] == "OOM" and rows["broken"]["acc"] is None
    shares = experiments.stage_shares(made).first()
    assert shares["feat_share"] + shares["emb_share"] + shares["select_share"] == pytest.approx(1)
    assert experiments.compare(made, "broken").first()["at_least"]
    cost = experiments.plan_cost(spark, lambda: spark.range(1000).groupBy(F.col("id") % 7).count().collect())
    assert cost["jobs"] >= 1 and cost["shuffle_rows"] >= 7 and cost["shuffle_bytes"] > 0


def rows_of(rows):
    return sorted((tuple(round(x, 6) + 0.0 if isinstance(x, float) else x for x in r) for r in rows), key=str)


@pytest.mark.parametrize("name", ["rates_block_pairs", "range_sum_cells", "planted_expected_edges", "edges_shared_lines", "edges_line_stars", "affected_region_day", "op_window_rank", "walk_through", "edges_nearest", "partition_document_lines", "base_components"])
def test_registered_queries_against_sql(spark, name):
    queries.load_all()
    base = duckdb.connect()
    for f in Path(SF).glob("*.parquet"):
        base.execute(f"CREATE VIEW {f.stem} AS SELECT * FROM '{f}'")
    found = queries.QUERIES[name](spark, SF)
    columns = sorted(found.columns)
    told = base.execute(f"SELECT {', '.join(columns)} FROM ({queries.ORACLES[name]}) x").fetchall()
    assert rows_of(map(tuple, found.select(*columns).collect())) == rows_of(told)


def test_matrix_of_a_slice():
    import pyarrow as pa

    rows = pa.array([[1.0, 2.0], [3.0, 4.0], [5.0, 6.0]], pa.list_(pa.float32()))
    assert matrix(rows.slice(1), 2).tolist() == [[3.0, 4.0], [5.0, 6.0]]
