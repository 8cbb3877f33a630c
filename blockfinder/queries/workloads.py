"""The experiments as queries: tables of quality, stages and ablations, sweeps, the stream in ten batches, and controls."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from ..operators import baselines, bisect, features, generator, gnn, graph, metrics, neighbours
from ..operators.graph import Graph
from ..plans import experiments
from ..plans.pipeline import partition
from ..plans.state import settle
from ..streaming import updates
from . import query
from .tables import OFFSET, arcs_sql, customer_supplier, line_graph, planted, table

DEGREE = 40.0


def small(spark, sf, seed=0):
    """The smallest size: customers in their nations."""
    p, g = planted(spark, sf, "customer", "c_custkey", "c_nationkey", seed=seed, mean_degree=DEGREE)
    return "customers in nations", seed, p.nodes, g


def middle(spark, sf):
    """Sizes above it: parts in their brands, and documents in drawn blocks."""
    for name, t, key, block in (("parts in brands", "part", "p_partkey", "p_brand"), ("documents, blocks drawn", "documents", "doc_id", None)):
        p, g = planted(spark, sf, t, key, block, mean_degree=DEGREE)
        yield name, 0, p.nodes, g


def rounded(df):
    return df.select([F.round(c, 4).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


@query()
def table_methods(spark, sf):
    """Both variants and the five other methods on one graph: status, quality, seconds."""
    return rounded(experiments.quality_table(spark, [small(spark, sf)], limit_s=120.0))


VARIANTS = {k: experiments.METHODS[k] for k in ("cut", "mod")}


@query()
def table_methods_larger(spark, sf):
    """The variants and the methods that end there, on the next sizes."""
    some = VARIANTS | {"parallel inference": experiments.METHODS["parallel inference"], "greedy rounds": lambda g: baselines.greedy_modularity(g)}
    return rounded(experiments.quality_table(spark, middle(spark, sf), some, limit_s=120.0))


@query()
def table_means(spark, sf):
    """Means over five graphs of one size, and the speed-up over parallel inference."""
    some = VARIANTS | {"parallel inference": experiments.METHODS["parallel inference"]}
    made = experiments.quality_table(spark, [small(spark, sf, seed) for seed in range(5)], some, limit_s=120.0)
    faster = experiments.compare(made, "parallel inference").drop("workload", "at_least")
    return rounded(experiments.summarise(made).join(faster, "method", "left"))


@query()
def table_stages(spark, sf):
    """Seconds and shares of the three stages."""
    return rounded(experiments.stage_shares(experiments.quality_table(spark, [small(spark, sf), *middle(spark, sf)], VARIANTS)))


GATE = "VALUES ('customers in nations', 'cut', true, true), ('customers in nations', 'mod', true, true), ('parts in brands', 'cut', true, true), ('parts in brands', 'mod', true, true), ('documents, blocks drawn', 'cut', true, true), ('documents, blocks drawn', 'mod', true, true)"


@query(f"SELECT * FROM ({GATE}) t(workload, method, accurate, blocks_found)")
def gate_quality(spark, sf):
    """Whether the variants reach an accuracy of 0.99 and miss the number of blocks by at most two."""
    made = experiments.quality_table(spark, [small(spark, sf), *middle(spark, sf)], VARIANTS)
    return made.select("workload", "method", (F.col("acc") >= 0.99).alias("accurate"), (F.abs(F.col("k_found") - F.col("k_true")) <= 2).alias("blocks_found"))


def ablations(spark, sf):
    _, _, truth, g = small(spark, sf)
    rows = []
    for kind in ("cut", "mod"):
        for left_out in (None, "no_features", "no_embedding"):
            s = metrics.scores(truth, partition(g, kind, ablation=left_out).blocks)
            rows.append((kind, left_out or "full", *[float(s[c]) for c in ("acc", "ari", "f1", "recall", "precision")], s["k_found"]))
    return spark.createDataFrame(rows, "method string, ablation string, acc double, ari double, f1 double, recall double, precision double, k_found long")


@query()
def table_ablation(spark, sf):
    """Both variants whole, without random features, and without convolution."""
    return rounded(ablations(spark, sf))


@query("SELECT * FROM (VALUES ('cut', true, true), ('mod', true, true)) t(method, features_alike, embedding_needed)")
def gate_ablation(spark, sf):
    """Leaving the features out changes little; leaving the convolution out costs accuracy, more than a hundredth."""
    rows = ablations(spark, sf).groupBy("method").pivot("ablation", ["full", "no_features", "no_embedding"]).agg(F.first("acc"))
    return rows.select("method", (F.abs(F.col("full") - F.col("no_features")) < 0.02).alias("features_alike"), (F.col("full") - F.col("no_embedding") > 0.01).alias("embedding_needed"))


@query()
def sweep_hardness(spark, sf):
    """Accuracy of the cut variant as the ratio and the spread of block sizes change, with both laws of the rates."""
    nodes = table(spark, sf, "customer").select(F.col("c_custkey").alias("id"))
    rows = []
    for even in ("blocks", "totals"):
        for ratio in (1.5, 2.5, 5.0):
            for heterogeneity in (1.0, 3.0):
                p = generator.benchmark_params(nodes, ratio=ratio, heterogeneity=heterogeneity, mean_degree=DEGREE, even=even)
                g = graph.build(generator.sample(p, "skip", 0), nodes, "src", "dst")
                s = metrics.scores(p.nodes, partition(g, "cut").blocks)
                rows.append((even, ratio, heterogeneity, float(s["acc"]), s["k_true"], s["k_found"]))
    return rounded(spark.createDataFrame(rows, "even string, ratio double, heterogeneity double, acc double, k_true long, k_found long"))


@query()
def generator_scaling(spark, sf):
    """Seconds of the exact sampler as nodes and edges grow."""
    rows = []
    for name, key in (("customer", "c_custkey"), ("part", "p_partkey"), ("orders", "o_orderkey"), ("lineitem", None)):
        ids = table(spark, sf, name)
        nodes = ids.select(F.col(key).alias("id")) if key else ids.select(F.xxhash64(*ids.columns).alias("id")).distinct()
        p = generator.benchmark_params(nodes, mean_degree=DEGREE)
        began = time.perf_counter()
        edges = generator.sample(p, "skip", 0).count()
        took = time.perf_counter() - began
        rows.append((name, p.nodes.count(), edges, took, took / max(1, edges) * 1e6))
    return rounded(spark.createDataFrame(rows, "graph string, n long, edges long, seconds double, microseconds_an_edge double"))


@query()
def stream_ten_batches(spark, sf):
    """A planted graph whose last half comes in ten batches: after each, the blocks and the agreement with the planted ones."""
    p, g = planted(spark, sf, "customer", "c_custkey", "c_mktsegment", ratio=8.0, mean_degree=20.0)
    edges = g.arcs.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"))
    part = F.pmod(F.xxhash64("a", "b"), F.lit(20))
    state = updates.start(graph.build(edges.where(part >= 10)), "cut", (64, 64, 64))
    rows = []
    for k in range(10):
        state = updates.apply_batch(state, edges.where(part == k), "touched")
        s = metrics.scores(p.nodes, state.blocks)
        rows.append((k, state.graph.m, s["k_found"], float(s["acc"])))
    s = metrics.scores(p.nodes, updates.refit(state).blocks)
    rows.append((10, state.graph.m, s["k_found"], float(s["acc"])))
    return rounded(spark.createDataFrame(rows, "batch int, m long, k_found long, acc double"))


def divided_sql(name: str) -> str:
    """CTEs that divide each set of ``name`` (path, id, x) where the squared error is least: ``name``_d (path, id, x, next)."""
    w = "OVER (PARTITION BY path ORDER BY x, id"
    return (
        f"{name}_o AS (SELECT path, x, row_number() {w}) AS k, sum(x) {w} ROWS UNBOUNDED PRECEDING) AS s, lead(x) {w}) AS beyond, count(*) OVER (PARTITION BY path) AS n, sum(x) OVER (PARTITION BY path) AS t FROM {name}), "
        f"{name}_c AS (SELECT path, arg_max(x, s * s / k + (t - s) * (t - s) / (n - k)) AS edge FROM {name}_o WHERE x < beyond GROUP BY path), "
        f"{name}_h AS (SELECT path, id, x, x > edge AS high FROM {name} JOIN {name}_c USING (path)), "
        f"{name}_f AS (SELECT path, arg_min(high, id) AS first FROM {name}_h GROUP BY path), "
        f"{name}_d AS (SELECT path, id, x, path || CASE WHEN high = first THEN '0' ELSE '1' END AS next FROM {name}_h JOIN {name}_f USING (path))"
    )


WALK_POINTS = "a AS (SELECT '' AS path, CAST(c_nationkey AS BIGINT) AS id, avg(c_acctbal) AS x FROM customer WHERE c_nationkey IS NOT NULL AND c_acctbal IS NOT NULL GROUP BY c_nationkey)"
WALK_COUNTS = "SELECT path, count(*) AS n, count(*) FILTER (WHERE next = path || '0') AS n0, count(*) FILTER (WHERE next = path || '1') AS n1 FROM {0}_d GROUP BY path"


@query(f"WITH {WALK_POINTS}, {divided_sql('a')}, b AS (SELECT next AS path, id, x FROM a_d), {divided_sql('b')} {WALK_COUNTS.format('a')} UNION ALL {WALK_COUNTS.format('b')}")
def walk_through(spark, sf):
    """The nations by their customers' mean balance: the first division and those of its halves, each the best of two-means; sides are told by their least nation."""
    points = table(spark, sf, "customer").where("c_nationkey is not null and c_acctbal is not null").groupBy(F.col("c_nationkey").cast("long").alias("id")).agg(F.avg("c_acctbal").alias("x"))
    assign = settle(points.select(F.lit("").alias("path"), "id", F.lit(1).cast("long").alias("deg"), F.array(F.col("x").cast("float")).alias("v")))
    out = []
    for _ in range(2):
        sets = assign.groupBy("path").agg(F.count(F.lit(1)).alias("n"), (F.min(F.col("v")[0]) < F.max(F.col("v")[0])).alias("apart")).where("apart")
        sizes = {r["path"]: r["n"] for r in sets.collect()}
        planes = bisect.two_means(assign, sizes, n_init=200, init="far") if sizes else {}
        sided = settle(bisect.assign_side(assign, planes))
        first = sided.groupBy("path").agg(F.min_by("side", "id").alias("first"))
        assign = settle(sided.join(F.broadcast(first), "path").select(F.concat("path", (F.col("side") != F.col("first")).cast("int").cast("string")).alias("path"), "id", "deg", "v"))
        own, last = F.expr("substring(path, 1, length(path) - 1)").alias("path"), F.substring("path", -1, 1)
        out.append(assign.groupBy(own).agg(F.count(F.lit(1)).alias("n"), F.count(F.when(last == "0", 1)).alias("n0"), F.count(F.when(last == "1", 1)).alias("n1")))
    return out[0].unionByName(out[1])


NEAREST_SQL = "WITH v AS (SELECT vec_id AS id, embedding AS e FROM embeddings), d AS (SELECT a.id AS a, b.id AS b, list_sum(list_transform(range(1, 65), lambda i: (a.e[i]::DOUBLE - b.e[i]::DOUBLE) * (a.e[i]::DOUBLE - b.e[i]::DOUBLE))) AS far FROM v a JOIN v b ON a.id <> b.id), r AS (SELECT a, b, far, row_number() OVER (PARTITION BY a ORDER BY far, b) AS k FROM d) SELECT a, b, round(far, 6) AS far FROM r WHERE k <= 5"


def embedding_rows(spark, sf):
    return table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))


@query(NEAREST_SQL)
def edges_nearest(spark, sf):
    """The five nearest others of each given vector."""
    return neighbours.nearest(embedding_rows(spark, sf), 5).select("a", "b", F.round("far", 6).alias("far"))


@query()
def partition_nearest(spark, sf):
    """Blocks of the graph of nearest neighbours, by given vectors and by its own embedding, against chance labels."""
    from ..operators import selection

    rows = embedding_rows(spark, sf)
    g = graph.build(neighbours.nearest(rows, 5).select("a", "b"), rows.select("id"))
    labels = table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("label").cast("long").alias("block"))
    out = []
    for name, blocks in (("given vectors", selection.hierarchical(g, rows)[0]), ("embedding of the graph", partition(g, "cut").blocks)):
        s = metrics.scores(labels, blocks)
        out.append((name, g.n, g.m, s["k_found"], float(s["ari"]), metrics.number(metrics.modularity_df(g, blocks))))
    return rounded(spark.createDataFrame(out, "method string, n long, m long, k_found long, label_ari double, modularity double"))


def covered(spark, g: Graph, kind: str = "cut"):
    """One row: nodes, blocks that are whole, and whether the division beats a single block."""
    blocks = partition(g, kind).blocks
    placed = blocks.agg(F.count(F.lit(1)).alias("rows"), F.countDistinct("id").alias("nodes"))
    score = metrics.number(metrics.modularity_df(g, blocks))
    return placed.select("rows", "nodes", F.lit(score >= 0).alias("gains"))


SIDES = "SELECT o_custkey AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey UNION SELECT l_suppkey + {0} FROM lineitem JOIN orders ON l_orderkey = o_orderkey".format(OFFSET)


@query(f"SELECT count(*) AS rows, count(*) AS nodes, true AS gains FROM ({SIDES}) s")
def partition_customer_supplier(spark, sf):
    return covered(spark, graph.build(customer_supplier(spark, sf)))


@query("SELECT count(*) AS rows, count(*) AS nodes, true AS gains FROM (SELECT user_id FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY 1 UNION ALL SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) + 1000000000 FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY 1) s")
def partition_user_key(spark, sf):
    from .tables import user_key

    return covered(spark, graph.build(user_key(spark, sf)), "mod")


@query("SELECT count(*) AS documents, true AS whole, true AS gains FROM documents")
def partition_document_lines(spark, sf):
    """Documents and the lines that two or more of them hold, as a graph of both kinds: no line is too crowded, and no pair is listed."""
    docs, g = table(spark, sf, "documents").select(F.col("doc_id").alias("id")), line_graph(spark, sf)
    blocks = partition(g, "cut", (128,) * 4).blocks
    own = blocks.join(docs, "id", "left_semi")
    score = metrics.number(metrics.modularity_df(g, blocks))
    return own.agg(F.count(F.lit(1)).alias("documents"), (F.count(F.lit(1)) == F.countDistinct("id")).alias("whole")).withColumn("gains", F.lit(score >= 0))


@query()
def partition_nested(spark, sf):
    """Nations inside regions: edges within nations, fewer within regions, few beyond. How well the tree, cut at each depth, tells the regions, and its leaves the nations."""
    nation = table(spark, sf, "nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_regionkey").cast("int").alias("region"))
    nodes = table(spark, sf, "customer").join(F.broadcast(nation), "c_nationkey").select(F.col("c_custkey").cast("long").alias("id"), F.col("c_nationkey").cast("int").alias("b"), "region")
    base = generator.benchmark_params(nodes, mean_degree=DEGREE, block="b")
    region = {r["b"]: r["region"] for r in nodes.select("b", "region").distinct().collect()}
    own = {r: x for r, s, x in base.omega if r == s}
    low = min(x for r, s, x in base.omega if r != s)
    omega = [(r, s, own[r] * 0.7 if r == s else low * 6 if region[r] == region[s] else low * 0.35) for r, s, _ in base.omega]
    g = graph.build(generator.sample(generator.Params(base.nodes, omega), "skip", 0), nodes, "src", "dst")
    r = partition(g, "cut")
    regions = nodes.select("id", F.col("region").cast("long").alias("block"))
    rows = [("nations", -1, metrics.scores(base.nodes.select("id", "block"), r.blocks))]
    for depth in (1, 2, 3, 4):
        cut = r.blocks.select("id", F.xxhash64(F.substring("path", 1, depth)).alias("block"))
        rows.append(("regions", depth, metrics.scores(regions, cut)))
    return rounded(spark.createDataFrame([(n, d, s["k_found"], float(s["acc"]), float(s["ari"])) for n, d, s in rows], "truth string, depth int, k_found long, acc double, ari double"))


@query()
def plan_costs(spark, sf):
    """What the stages of a run read and shuffle, on graphs of two densities: rows grow with the arcs, jobs do not."""
    rows = []
    for degree in (20.0, 40.0):
        _, g = planted(spark, sf, "customer", "c_custkey", "c_nationkey", mean_degree=degree)
        y = features.project(g, "cut", 64)
        for name, run in (("features", lambda: y.count()), ("layers", lambda: gnn.forward(g, y, (64, 64, 64)).count())):
            cost = experiments.plan_cost(spark, run)
            rows.append((name, 2 * g.m, *[int(cost[c]) for c in ("jobs", "stages", "tasks", "rows_read", "shuffle_rows", "shuffle_bytes", "spill_bytes")]))
    return spark.createDataFrame(rows, "stage string, arcs long, jobs long, stages long, tasks long, rows_read long, shuffle_rows long, shuffle_bytes long, spill_bytes long")


@query(f"SELECT count(*) AS arcs FROM ({arcs_sql('SELECT DISTINCT o_custkey AS src, l_suppkey + 1000000000 AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey')})")
def arcs_customer_supplier(spark, sf):
    """Both directions of each edge, once."""
    return graph.both_ways(graph.canonical(customer_supplier(spark, sf))).agg(F.count(F.lit(1)).alias("arcs"))
