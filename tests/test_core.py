"""The methods against hand examples, dense algebra and brute force."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockfinder.functions.rng import gauss_block
from blockfinder.operators import baselines, bisect, features, generator, gnn, graph, metrics, selection
from blockfinder.operators.kernels import matrix
from blockfinder.plans.pipeline import partition

TRIANGLES = [(1, 2), (1, 3), (2, 3), (4, 5), (4, 6), (5, 6), (3, 4)]


def build(spark, pairs, nodes=None):
    return graph.build(spark.createDataFrame(pairs, "a long, b long"), None if nodes is None else spark.createDataFrame([(n,) for n in nodes], "id long"))


def blocks_of(spark, sides):
    return spark.createDataFrame(list(sides.items()), "id long, block long")


def dense(g):
    ids = sorted(r["id"] for r in g.nodes.collect())
    at = {i: k for k, i in enumerate(ids)}
    a = np.zeros((len(ids), len(ids)))
    for r in g.arcs.collect():
        a[at[r["src"]], at[r["dst"]]] = 1
    return ids, a


def rows_of(df, ids):
    table = df.select("id", "v").toArrow().sort_by("id")
    assert table["id"].to_pylist() == ids
    return matrix(table["v"].combine_chunks(), -1)


@pytest.fixture(scope="module")
def triangles(spark):
    return build(spark, [*TRIANGLES, (2, 1), (5, 5), (1, 2), (None, 3)])


@pytest.fixture(scope="module")
def planted(spark):
    params = generator.benchmark_params(spark.range(600), ratio=4.0, mean_degree=30.0, k=6, seed=2)
    return params, graph.build(generator.sample(params, "skip", 2), spark.range(600), "src", "dst")


def test_canonical_graph(triangles):
    assert (triangles.n, triangles.m) == (6, 7)
    assert {r["id"]: r["deg"] for r in triangles.nodes.collect()} == {1: 2, 2: 2, 3: 3, 4: 3, 5: 2, 6: 2}


def test_two_triangles(spark, triangles):
    halves = blocks_of(spark, {1: 1, 2: 1, 3: 1, 4: 4, 5: 4, 6: 4})
    assert metrics.number(metrics.ncut_df(triangles, halves)) == pytest.approx(1 / 7)
    assert metrics.number(metrics.ncut_trace_df(triangles, halves)) == pytest.approx(2 / 7)
    assert metrics.number(metrics.modularity_df(triangles, halves)) == pytest.approx(5 / 14)
    assert metrics.number(metrics.modularity_trace_df(triangles, halves)) == pytest.approx(5)
    assign = halves.select("id", F.lit("x").alias("subset"), "block")
    for scope in selection.SCOPES:
        assert selection.local_modularity(triangles, assign, scope).first()["score"] == pytest.approx(5 / 14)
    one = blocks_of(spark, {1: 1, 2: 1, 3: 1}).select("id", F.lit("x").alias("subset"), "block")
    assert selection.local_modularity(triangles, one, "subset").first()["score"] == pytest.approx(-1 / 7)
    assert selection.stays(3, 3, 7, 7, 1, 3, 3, 14, 2, "graph")
    assert not selection.stays(3, 3, 7, 7, 1, 3, 3, 14, 3, "graph")  # both halves must be over the floor
    assert selection.stays(9, 9, 10, 10, 5, 0, 0, 20, 2, "graph")  # a tie is a split


def test_features_match_dense_algebra(triangles):
    ids, a = dense(triangles)
    d, theta = a.sum(axis=1), gauss_block(3, np.array(ids), 5) * 5**-0.5
    full = a - np.outer(d, d) / d.sum()
    for kind, x in {"cut": a / np.sqrt(np.outer(d, d)), "mod": full * a, "mod_full": full}.items():
        assert rows_of(features.project(triangles, kind, 5, 3), ids) == pytest.approx(x @ theta, abs=1e-5)
        assert rows_of(features.project(triangles, kind, 5, 3, salt=3), ids) == pytest.approx(x @ theta, abs=1e-5)
        if kind != "mod_full":
            assert rows_of(features.from_factors(features.factored(triangles, kind, 5, 3), kind, 14), ids) == pytest.approx(x @ theta, abs=1e-5)


@pytest.mark.parametrize("how", ["broadcast", "blocks", "join"])
def test_forward_pass_matches_dense_algebra(triangles, how):
    ids, a = dense(triangles)
    hat = a + np.eye(len(a))
    hat = hat / np.sqrt(np.outer(hat.sum(axis=1), hat.sum(axis=1)))
    y = features.project(triangles, "cut", 6, 1)
    z = rows_of(y, ids).astype("f8")
    for k, (rows, columns) in enumerate([(6, 4), (4, 3)]):
        z = np.tanh(hat @ z @ gnn.weights(rows, columns, 1, k))
        z = z / np.linalg.norm(z, axis=1, keepdims=True)
    assert rows_of(gnn.forward(triangles, y, (6, 4, 3), 1, how=how), ids) == pytest.approx(z, abs=1e-5)
    assert np.linalg.norm(z, axis=1) == pytest.approx(np.ones(6))


def test_gaussian_law():
    x = gauss_block(1, np.arange(20_000), 8)
    assert abs(x.mean()) < 0.01 and abs(x.std() - 1) < 0.01 and abs(np.corrcoef(x.T) - np.eye(8)).max() < 0.03


def test_two_means_against_brute_force():
    rng = np.random.default_rng(5)
    for _ in range(5):
        z = np.concatenate([rng.normal(0, 0.3, (5, 2)), rng.normal(3, 0.3, (4, 2))])
        w, b = bisect.fit(z, np.arange(9), n_init=5)
        side = z @ w > b

        def error(s, z=z):
            return sum(((z[p] - z[p].mean(axis=0)) ** 2).sum() for p in (s, ~s) if p.any())

        best = min(error(np.array(s)) for s in itertools.product([False, True], repeat=9) if 0 < sum(s) < 9)
        assert error(side) == pytest.approx(best)
    assert not (np.ones((4, 2)) @ bisect.fit(np.ones((4, 2)), np.arange(4))[0] > bisect.fit(np.ones((4, 2)), np.arange(4))[1]).any()


def test_two_means_as_jobs_is_the_same_as_in_memory(spark):
    rng = np.random.default_rng(1)
    z = np.concatenate([rng.normal(0, 1.0, (200, 3)), rng.normal(2, 1.0, (150, 3))]).astype("f4")
    assign = spark.createDataFrame([("a" if k % 2 else "b", k, 1, row.tolist()) for k, row in enumerate(z)], "path string, id long, deg long, v array<float>").repartition(5)
    for rows in (40, 10_000):
        planes = bisect.two_means(assign, {"a": 175, "b": 175}, rows=rows)
        sides = {r["id"]: r["side"] for r in bisect.assign_side(assign, planes).collect()}
        for path, own in (("a", np.arange(1, 350, 2)), ("b", np.arange(0, 350, 2))):
            w, b = bisect.fit(z[own], own, rows=rows)
            assert planes[path][0] == pytest.approx(w) and planes[path][1] == pytest.approx(b)
            assert [sides[k] for k in own.tolist()] == (z[own].astype("f8") @ w > b).astype(int).tolist()


def test_planted_blocks_are_found(spark, planted):
    params, g = planted
    for kind in ("cut", "mod"):
        r = partition(g, kind, (128, 64, 32))
        assert metrics.scores(params.nodes, r.blocks)["acc"] > 0.99
        assert r.blocks.count() == r.blocks.select("id").distinct().count() == 600
        tree = {t["path"]: t for t in r.tree.collect()}
        leaves = {x["path"]: x["n"] for x in r.blocks.groupBy("path").agg(F.count(F.lit(1)).alias("n")).collect()}
        assert all(tree[p]["verdict"] == "stop" and tree[p]["n"] == n and n > 5 for p, n in leaves.items())
        gains = sum(2 / (2 * g.m) * (tree[p + "0"]["vol"] * tree[p + "1"]["vol"] / (2 * g.m) - t["cut"]) for p, t in tree.items() if t["verdict"] == "split")
        assert metrics.number(metrics.modularity_df(g, r.blocks)) == pytest.approx(gains)


def test_levels_as_jobs_give_the_same_blocks(spark, planted):
    _, g = planted
    z = partition(g, "cut", (128, 64, 32)).embedding
    for rows in (100, 32_768):
        found = [selection.hierarchical(g, z, local_below=n, rows=rows) for n in (600, 150, 1)]
        blocks = [{r["id"]: r["block"] for r in b.collect()} for b, _ in found]
        assert blocks[0] == blocks[1] == blocks[2]
        assert len({t.count() for _, t in found}) == 1


def test_sets_in_waves(spark, planted, monkeypatch):
    _, g = planted
    z = partition(g, "cut", (128, 64, 32)).embedding
    whole = {r["id"]: r["block"] for r in selection.hierarchical(g, z)[0].collect()}
    monkeypatch.setattr(selection, "OPEN_AT_ONCE", 2)
    assert {r["id"]: r["block"] for r in selection.hierarchical(g, z, local_below=20)[0].collect()} == whole


def test_partitioning_does_not_change_blocks(spark, planted):
    params, _ = planted
    found = []
    for n in ("3", "11"):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        g = graph.build(generator.sample(params, "skip", 2).repartition(int(n)), spark.range(600), "src", "dst")
        found.append({r["id"]: r["block"] for r in partition(g, "mod", (64, 32)).blocks.collect()})
    spark.conf.set("spark.sql.shuffle.partitions", "8")
    assert found[0] == found[1]


def test_printed_scope_shreds_and_complete_graph_stays(spark, planted):
    params, g = planted
    shredded = partition(g, "cut", (128, 64, 32), null_scope="subset").blocks.select("block").distinct().count()
    assert shredded > 12
    complete = build(spark, [(a, b) for a in range(30) for b in range(a)])
    for kind in ("cut", "mod"):
        assert partition(complete, kind, (16, 8)).blocks.select("block").distinct().count() == 1


def test_degenerate_graphs(spark):
    empty = build(spark, [], [])
    assert partition(empty, "cut", (8, 4)).blocks.count() == 0
    lonely = build(spark, [], [1, 2, 3])
    assert {r["block"] for r in partition(lonely, "cut", (8, 4)).blocks.collect()} == {1}
    assert partition(lonely, "cut", (8, 4), isolates="singleton").blocks.select("block").distinct().count() == 3
    for pairs in ([(1, 2)], [(1, k) for k in range(2, 9)], [(k, k + 1) for k in range(9)]):
        r = partition(build(spark, pairs, [99]), "mod", (8, 4))
        assert r.blocks.count() == len({x for p in pairs for x in p} | {99})


def test_metrics(spark):
    t = blocks_of(spark, dict.fromkeys(range(3), 0) | dict.fromkeys(range(3, 6), 1))
    same = metrics.scores(t, t.select("id", (F.col("block") + 7).alias("block")))
    assert same["acc"] == same["ari"] == same["f1"] == 1
    one = metrics.scores(t, t.select("id", F.lit(0).alias("block")))
    assert (one["recall"], one["precision"], one["ari"], one["acc"]) == (1, pytest.approx(0.4), 0, 0.5)
    rng = np.random.default_rng(0)
    for _ in range(20):
        gain = rng.integers(0, 9, (rng.integers(1, 5), rng.integers(1, 6)))
        small, large = sorted(gain.shape)
        wide = gain if gain.shape[0] <= gain.shape[1] else gain.T
        assert metrics.matching(gain) == max(sum(wide[k, c] for k, c in enumerate(p)) for p in itertools.permutations(range(large), small))


def test_generator_law(spark):
    nodes = spark.range(60).withColumn("b", (F.col("id") % 3).cast("int"))
    params = generator.benchmark_params(nodes, mean_degree=12.0, block="b", simple=False)
    mass = {(r["r"], r["s"]): r["mass"] for r in generator.rates_df(params).collect()}
    place = {r["id"]: r["block"] for r in params.nodes.collect()}
    for method in (generator.skip, generator.split):
        seen = dict.fromkeys(mass, 0)
        for seed in range(12):
            rows = method(params, seed).collect()
            assert all(r["src"] < r["dst"] and r["weight"] >= 1 for r in rows) and len({(r["src"], r["dst"]) for r in rows}) == len(rows)
            for r in rows:
                key = tuple(sorted((place[r["src"]], place[r["dst"]])))
                seen[key] += r["weight"]
        z = [(seen[k] - 12 * m) / (12 * m) ** 0.5 for k, m in mass.items()]
        assert max(map(abs, z)) < 4.5
    again = [sorted(map(tuple, generator.skip(params, 3, strip_edges=20).collect())) for _ in range(2)]
    assert again[0] == again[1]


def test_range_sum():
    rng = np.random.default_rng(0)
    a, b = rng.random(4), rng.random(3)
    cells = (2.0 * np.outer(a, b)).reshape(-1)
    own = np.array([2.0 * a[i] * a[j] for i in range(4) for j in range(i + 1, 4)])
    for first in range(12):
        for last in range(first, 12):
            assert generator.range_sum(a, b, 2.0, first, last) == pytest.approx(cells[first : last + 1].sum())
    assert generator.range_sum(a, None, 2.0, 1, 4) == pytest.approx(own[1:5].sum())


def test_comparison_methods(spark, planted):
    params, g = planted
    for method in (baselines.greedy_modularity, baselines.sbm_mcmc, baselines.spectral_modularity, baselines.belief_propagation, baselines.label_propagation):
        assert metrics.scores(params.nodes, method(g))["acc"] > 0.7
    assert baselines.components(build(spark, [(1, 2), (2, 3), (5, 9)], [7])).select("block").distinct().count() == 3
    cost = baselines.merge_costs(np.array([[4.0, 1, 2], [1, 6, 0], [2, 0, 8]]))
    table = np.array([[4.0, 1, 2], [1, 6, 0], [2, 0, 8]])

    def fit(t):
        v = t.sum(axis=1)
        return (baselines.xlogx(t).sum() - 2 * baselines.xlogx(v).sum()) / 2

    joined = np.array([[4 + 6 + 2.0, 2], [2, 8]])
    assert cost[0, 1] == pytest.approx(fit(table) - fit(joined))


def test_streamed_edges_reach_the_full_result(spark, planted):
    from blockfinder.streaming import updates

    _, g = planted
    edges = g.arcs.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"))
    late = F.pmod(F.xxhash64("a", "b"), F.lit(40)) == 0
    state = updates.start(graph.build(edges.where(~late), spark.range(600)), "cut", (64, 32))
    state = updates.apply_batch(state, edges.where(late), "ball")
    assert updates.apply_batch(state, edges.where(late), "ball") is state  # given again, nothing changes
    full = updates.start(graph.build(edges, spark.range(600)), "cut", (64, 32))
    ids = list(range(600))
    assert rows_of(state.embedding, ids) == pytest.approx(rows_of(full.embedding, ids), abs=1e-4)
    assert metrics.scores(full.blocks, updates.refit(state).blocks)["acc"] > 0.99
    assert metrics.scores(full.blocks, state.blocks)["acc"] > 0.9  # old planes stay where their verdict does
    before = graph.build(edges.where(~late), spark.range(600))
    added = updates.new_edges(before.arcs.where("src < dst"), edges.where(late))
    factors = updates.feature_delta(features.factored(before, "mod", 8, 1), before, updates.grow(before, added), added, 8, 1)
    expected = {r["id"]: (r["p1"], r["p2"]) for r in features.factored(full.graph, "mod", 8, 1).collect()}
    for r in factors.collect():
        assert r["p1"] == pytest.approx(expected[r["id"]][0], abs=1e-3) and r["p2"] == pytest.approx(expected[r["id"]][1], abs=2e-2)


def test_edge_files(spark, triangles, tmp_path):
    from blockfinder.sources import files

    edges = triangles.arcs.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    for form in ("parquet", "orc", "json", "csv", "tsv"):
        files.write_edges(edges, f"{tmp_path}/{form}", form)
        assert graph.build(files.read_edges(spark, f"{tmp_path}/{form}", form)).m == 7
