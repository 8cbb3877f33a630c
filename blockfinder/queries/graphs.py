"""Graph building, structure, features, measures and split decisions, each with SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.rng import gauss_sql, hash01, hash01_sql
from ..operators import features, generator, gnn, graph, metrics, selection
from . import query
from .tables import CUSTOMER_SUPPLIER, LEAST_LINE, PART, SUPPLIER, USER_KEY, coorder_pairs, customer_supplier, document_lines, graph_ctes, part_graph, shared_lines, supplier_graph, table, user_key

WIDTH = 4
SEED = 7
NATION_SQL = "SELECT c_custkey AS id, c_nationkey AS block FROM customer"
BRAND_SQL = "SELECT p_partkey AS id, CAST(dense_rank() OVER (ORDER BY p_brand) AS BIGINT) AS block FROM part"


def brand_blocks(spark, sf):
    names = table(spark, sf, "part").select("p_brand").distinct()
    from pyspark.sql import Window

    ranked = names.withColumn("block", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("p_brand")).cast("long"))  # 25 brands
    return table(spark, sf, "part").join(F.broadcast(ranked), "p_brand").select(F.col("p_partkey").alias("id"), "block")


@query(SUPPLIER)
def edges_supplier_coorder(spark, sf):
    return graph.canonical(coorder_pairs(spark, sf, "l_suppkey"))


@query(PART)
def edges_part_coorder(spark, sf):
    return graph.canonical(coorder_pairs(spark, sf, "l_partkey"))


@query(CUSTOMER_SUPPLIER)
def edges_customer_supplier(spark, sf):
    return graph.canonical(customer_supplier(spark, sf))


@query(USER_KEY)
def edges_user_key(spark, sf):
    return graph.canonical(user_key(spark, sf))


LINES_SQL = f"lines AS (SELECT DISTINCT doc_id, trim(u.line, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) u WHERE length(trim(u.line, ' ')) >= {LEAST_LINE}), held AS (SELECT line, count(*) AS n, min(doc_id) AS least FROM lines GROUP BY line HAVING count(*) > 1)"


@query(f"WITH {LINES_SQL} SELECT doc_id, md5(line) AS line_md5 FROM lines JOIN held USING (line)")
def edges_shared_lines(spark, sf):
    """Documents and the lines that they share with others: however crowded a line is, it has one edge for each document."""
    return shared_lines(spark, sf).select("doc_id", F.md5("line").alias("line_md5"))


@query(f"WITH {LINES_SQL} SELECT DISTINCT least AS src, doc_id AS dst FROM lines JOIN held USING (line) WHERE doc_id > least")
def edges_line_stars(spark, sf):
    """Links between documents that connect whatever shares a line: each line's documents with the least one of them."""
    rows = document_lines(spark, sf)
    least = rows.groupBy("line").agg(F.min("doc_id").alias("src"), F.count(F.lit(1)).alias("n")).where("n > 1")
    return rows.join(least, "line").where("doc_id > src").select("src", F.col("doc_id").alias("dst")).distinct()


@query(f"WITH {LINES_SQL} SELECT md5(line) AS line_md5, n FROM held WHERE n > 50")
def crowded_lines(spark, sf):
    """A report of the lines of more than 50 documents."""
    return graph.crowded(document_lines(spark, sf), F.col("doc_id"), F.col("line"), 50).select(F.md5("key").alias("line_md5"), "n")


@query("SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS target FROM pages")
def edges_page_links(spark, sf):
    return table(spark, sf, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1)).alias("target")).distinct()


@query("SELECT b.item_id, d.doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def edges_benchmark_passages(spark, sf):
    passages = table(spark, sf, "benchmark").select("item_id", F.col("text").alias("passage"))  # a fixed query set, held against all documents
    return table(spark, sf, "documents").select("doc_id", "text").join(F.broadcast(passages), F.col("text").contains(F.col("passage"))).select("item_id", "doc_id")


@query(f"WITH {graph_ctes(PART)} SELECT id, deg FROM deg")
def degrees_part(spark, sf):
    return graph.degrees(graph.both_ways(graph.canonical(coorder_pairs(spark, sf, "l_partkey"))))


@query(f"WITH {graph_ctes(PART)} SELECT count(*) AS n, CAST(sum(deg) / 2 AS BIGINT) AS m, min(deg) AS deg_min, max(deg) AS deg_max, round(sum(deg) / (CAST(count(*) AS DOUBLE) * (count(*) - 1)), 6) AS density FROM deg")
def graph_describe(spark, sf):
    return graph.describe_df(part_graph(spark, sf))


@query(f"WITH {graph_ctes(PART)} SELECT deg, count(*) AS nodes FROM deg GROUP BY deg")
def degree_histogram(spark, sf):
    return graph.degrees(graph.both_ways(graph.canonical(coorder_pairs(spark, sf, "l_partkey")))).groupBy("deg").agg(F.count(F.lit(1)).alias("nodes"))


@query(f"WITH {graph_ctes(SUPPLIER)} SELECT src AS id, count(*) AS deg, string_agg(CAST(dst AS VARCHAR), ',' ORDER BY dst) AS neighbours FROM arcs GROUP BY src")
def adjacency_lists(spark, sf):
    arcs = graph.both_ways(graph.canonical(coorder_pairs(spark, sf, "l_suppkey")))
    return arcs.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("deg"), F.concat_ws(",", F.transform(F.sort_array(F.collect_list("dst")), lambda x: x.cast("string"))).alias("neighbours"))


@query(f"SELECT p_partkey AS id FROM part WHERE p_partkey NOT IN (SELECT src FROM ({PART}) UNION SELECT dst FROM ({PART}))")
def isolated_parts(spark, sf):
    arcs = graph.both_ways(graph.canonical(coorder_pairs(spark, sf, "l_partkey")))
    return table(spark, sf, "part").select(F.col("p_partkey").alias("id")).join(arcs.select(F.col("src").alias("id")), "id", "left_anti")


@query(f"WITH {graph_ctes(CUSTOMER_SUPPLIER)}, one AS (SELECT DISTINCT dst AS id FROM arcs WHERE src = 1), two AS (SELECT DISTINCT dst AS id FROM arcs WHERE src IN (SELECT id FROM one)) SELECT CAST(1 AS BIGINT) AS id, 0 AS hop UNION ALL SELECT id, 1 FROM one WHERE id <> 1 UNION ALL SELECT id, 2 FROM two WHERE id <> 1 AND id NOT IN (SELECT id FROM one)")
def two_hop_neighbours(spark, sf):
    arcs = graph.both_ways(graph.canonical(customer_supplier(spark, sf)))
    return graph.neighbourhood(arcs, spark.createDataFrame([(1,)], "id long"), 2)


@query(f"WITH {graph_ctes(CUSTOMER_SUPPLIER)}, strong AS (SELECT id FROM deg WHERE deg >= 30) SELECT src, dst FROM e WHERE src IN (SELECT id FROM strong) AND dst IN (SELECT id FROM strong)")
def kcore_step(spark, sf):
    return graph.core_step(graph.canonical(customer_supplier(spark, sf)), 30)


@query(f"WITH e AS ({SUPPLIER}) SELECT a.src AS id, count(*) AS triangles FROM e a JOIN e b ON a.src = b.src AND a.dst < b.dst JOIN e c ON c.src = a.dst AND c.dst = b.dst GROUP BY a.src")
def triangle_counts(spark, sf):
    e = graph.canonical(coorder_pairs(spark, sf, "l_suppkey"))
    a, b, c = e.select("src", F.col("dst").alias("x")), e.select("src", F.col("dst").alias("y")), e.select(F.col("src").alias("x"), F.col("dst").alias("y"))
    return a.join(b, "src").where("x < y").join(c, ["x", "y"]).groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("triangles"))


ENDS = "FROM arcs JOIN deg s ON s.id = arcs.src JOIN deg d ON d.id = arcs.dst"
CUT_W, MOD_W = "(1 / sqrt(CAST(s.deg AS DOUBLE) * d.deg))", "(1 - CAST(s.deg AS DOUBLE) * d.deg / (2 * (SELECT m FROM tot)))"


@query(f"WITH {graph_ctes(PART)} SELECT src, dst, round({CUT_W}, 6) AS w {ENDS}")
def weights_cut(spark, sf):
    return features.structure(part_graph(spark, sf), "cut").select("src", "dst", F.round("w", 6).alias("w"))


@query(f"WITH {graph_ctes(PART)} SELECT src, dst, round({MOD_W}, 6) AS w {ENDS}")
def weights_mod(spark, sf):
    return features.structure(part_graph(spark, sf), "mod").select("src", "dst", F.round("w", 6).alias("w"))


@query(f"WITH {graph_ctes(SUPPLIER)} SELECT s.id AS src, d.id AS dst, round((CASE WHEN arcs.src IS NULL THEN 0 ELSE 1 END) - CAST(s.deg AS DOUBLE) * d.deg / (2 * (SELECT m FROM tot)), 6) AS q FROM deg s CROSS JOIN deg d LEFT JOIN arcs ON arcs.src = s.id AND arcs.dst = d.id")
def weights_mod_full_rankone(spark, sf):
    g = supplier_graph(spark, sf)
    return features.dense_modularity(g).select("src", "dst", F.round("q", 6).alias("q"))


def project_sql(weight: str) -> str:
    return f"SELECT arcs.src AS id, dim, sum({weight} * {gauss_sql(SEED, 'arcs.dst', 'dim')} * {WIDTH**-0.5!r}) AS val {ENDS} CROSS JOIN (SELECT unnest(range({WIDTH})) AS dim) x GROUP BY arcs.src, dim"


def rounded(df):
    return df.select("id", F.col("dim").cast("long").alias("dim"), (F.round("val", 6) + 0.0).alias("val"))


def rounded_sql(source: str) -> str:
    return f"SELECT id, CAST(dim AS BIGINT) AS dim, round(val, 6) + 0.0 AS val FROM {source}"


@query(f"WITH {graph_ctes(SUPPLIER)}, y AS ({project_sql(CUT_W)}) {rounded_sql('y')}")
def project_cut(spark, sf):
    return rounded(features.project_long(supplier_graph(spark, sf), "cut", WIDTH, SEED))


@query(f"WITH {graph_ctes(SUPPLIER)}, y AS ({project_sql(MOD_W)}) {rounded_sql('y')}")
def project_mod(spark, sf):
    return rounded(features.project_long(supplier_graph(spark, sf), "mod", WIDTH, SEED))


PLAIN = f"{gauss_sql(SEED, 'arcs.dst', 'dim')} * {WIDTH**-0.5!r}"


@query(f"WITH {graph_ctes(SUPPLIER)}, f AS (SELECT arcs.src AS id, dim, sum({PLAIN}) AS p1, sum(d.deg * {PLAIN}) AS p2, any_value(s.deg) AS deg {ENDS} CROSS JOIN (SELECT unnest(range({WIDTH})) AS dim) x GROUP BY arcs.src, dim) SELECT id, CAST(dim AS BIGINT) AS dim, round(p1, 5) + 0.0 AS p1, round(p2, 5) + 0.0 AS p2, round(p1 - deg / (2.0 * (SELECT m FROM tot)) * p2, 5) + 0.0 AS val FROM f")
def project_mod_factored(spark, sf):
    from ..functions.rng import gauss

    g = supplier_graph(spark, sf)
    theta = gauss(SEED, F.col("dst"), F.col("dim")) * WIDTH**-0.5
    rows = g.arcs.select("src", "dst", "dsrc", "ddst", F.explode(F.sequence(F.lit(0), F.lit(WIDTH - 1))).alias("dim"))
    f = rows.groupBy(F.col("src").alias("id"), "dim").agg(F.sum(theta).alias("p1"), F.sum(F.col("ddst") * theta).alias("p2"), F.first("dsrc").alias("deg"))
    return f.select("id", F.col("dim").cast("long").alias("dim"), (F.round("p1", 5) + 0.0).alias("p1"), (F.round("p2", 5) + 0.0).alias("p2"), (F.round(F.col("p1") - F.col("deg") / float(2 * g.m) * F.col("p2"), 5) + 0.0).alias("val"))


@query(
    f"WITH {graph_ctes(SUPPLIER)}, t AS (SELECT id, deg, dim, {gauss_sql(SEED, 'id', 'dim')} * {WIDTH**-0.5!r} AS g FROM deg CROSS JOIN (SELECT unnest(range({WIDTH})) AS dim) x), whole AS (SELECT dim, sum(deg * g) AS s FROM t GROUP BY dim), y AS (SELECT arcs.src AS id, dim, sum(g) AS v FROM arcs JOIN t ON t.id = arcs.dst GROUP BY arcs.src, dim), out AS (SELECT y.id, y.dim, v - deg.deg / (2.0 * (SELECT m FROM tot)) * s AS val FROM y JOIN deg ON deg.id = y.id JOIN whole ON whole.dim = y.dim) {rounded_sql('out')}"
)
def project_mod_full(spark, sf):
    from ..functions.rng import gauss

    g = supplier_graph(spark, sf)
    theta = g.nodes.select("id", "deg", F.explode(F.sequence(F.lit(0), F.lit(WIDTH - 1))).alias("dim")).withColumn("g", gauss(SEED, F.col("id"), F.col("dim")) * WIDTH**-0.5)
    whole = theta.groupBy("dim").agg(F.sum(F.col("deg") * F.col("g")).alias("s"))
    y = g.arcs.select("src", F.col("dst").alias("id")).join(theta.select("id", "dim", "g"), "id").groupBy(F.col("src").alias("id"), "dim").agg(F.sum("g").alias("v"))
    return rounded(y.join(g.nodes, "id").join(F.broadcast(whole), "dim").select("id", "dim", (F.col("v") - F.col("deg") / float(2 * g.m) * F.col("s")).alias("val")))


def layer_sql(z: str, seed: int, columns: int) -> str:
    own = f"SELECT z.id, z.dim, z.val / sqrt(deg.deg + 1.0) AS val FROM {z} z JOIN deg ON deg.id = z.id"
    agg = f"SELECT id, dim, sum(val) AS val FROM (SELECT arcs.src AS id, o.dim, o.val FROM arcs JOIN ({own}) o ON o.id = arcs.dst UNION ALL SELECT id, dim, val FROM ({own}) p) q GROUP BY id, dim"
    return f"SELECT a.id, x.dim, tanh(sum(a.val * {gauss_sql(seed, 'a.dim', 'x.dim')} * {columns**-0.5!r}) / sqrt(any_value(deg.deg) + 1.0)) AS val FROM ({agg}) a JOIN deg ON deg.id = a.id CROSS JOIN (SELECT unnest(range({columns})) AS dim) x GROUP BY a.id, x.dim"


def norm_sql(z: str) -> str:
    return f"SELECT id, dim, CASE WHEN n > 0 THEN val / n ELSE 0 END AS val FROM (SELECT id, dim, val, sqrt(sum(val * val) OVER (PARTITION BY id)) AS n FROM {z}) w"


@query(f"WITH {graph_ctes(SUPPLIER)}, y AS ({project_sql(CUT_W)}), z AS ({layer_sql('y', 11, 3)}) {rounded_sql('z')}")
def conv_layer_one(spark, sf):
    g = supplier_graph(spark, sf)
    return rounded(gnn.layer_long(g, features.project_long(g, "cut", WIDTH, SEED), 3, WIDTH, 11))


@query(f"WITH {graph_ctes(SUPPLIER)}, y AS ({project_sql(CUT_W)}), z1 AS ({layer_sql('y', 11, 3)}), n1 AS ({norm_sql('z1')}), z2 AS ({layer_sql('n1', 12, 2)}), n2 AS ({norm_sql('z2')}) {rounded_sql('n2')}")
def conv_two_layers_norm(spark, sf):
    g = supplier_graph(spark, sf)
    z = gnn.normalise_long(gnn.layer_long(g, features.project_long(g, "cut", WIDTH, SEED), 3, WIDTH, 11))
    return rounded(gnn.normalise_long(gnn.layer_long(g, z, 2, 3, 12)))


@query("SELECT vec_id AS id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))), 6) AS size FROM embeddings")
def row_norms(spark, sf):
    from ..functions.vectors import norm

    return table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.round(norm(F.col("embedding")), 6).alias("size"))


# Measures of given partitions: the part graph by brand, the customer-supplier graph by parity of the id.

BLOCKED = f"{graph_ctes(PART)}, b AS ({BRAND_SQL}), bp AS (SELECT x.block AS r, y.block AS s, count(*) AS arcs FROM arcs JOIN b x ON x.id = arcs.src JOIN b y ON y.id = arcs.dst GROUP BY 1, 2), bs AS (SELECT r AS block, CAST(sum(arcs) AS BIGINT) AS vol, CAST(sum(CASE WHEN r = s THEN arcs ELSE 0 END) AS BIGINT) AS own, CAST(sum(CASE WHEN r <> s THEN arcs ELSE 0 END) AS BIGINT) AS cut FROM bp GROUP BY r)"


@query(f"WITH {BLOCKED} SELECT round(sum(CAST(cut AS DOUBLE) / vol) / 2, 6) AS ncut FROM bs")
def ncut_by_brand(spark, sf):
    return metrics.ncut_df(part_graph(spark, sf), brand_blocks(spark, sf)).select(F.round("ncut", 6).alias("ncut"))


@query(f"WITH {BLOCKED} SELECT round(sum(CAST(cut AS DOUBLE) / vol), 6) AS trace FROM bs")
def ncut_trace_by_brand(spark, sf):
    return metrics.ncut_trace_df(part_graph(spark, sf), brand_blocks(spark, sf)).select(F.round("trace", 6).alias("trace"))


@query(f"WITH {BLOCKED} SELECT round(sum(own / (2.0 * (SELECT m FROM tot)) - pow(vol / (2.0 * (SELECT m FROM tot)), 2)), 6) + 0.0 AS modularity FROM bs")
def modularity_by_brand(spark, sf):
    return metrics.modularity_df(part_graph(spark, sf), brand_blocks(spark, sf)).select((F.round("modularity", 6) + 0.0).alias("modularity"))


@query(f"WITH {BLOCKED} SELECT round(sum(own - CAST(vol AS DOUBLE) * vol / (2.0 * (SELECT m FROM tot))), 4) + 0.0 AS trace FROM bs")
def modularity_trace_by_brand(spark, sf):
    return metrics.modularity_trace_df(part_graph(spark, sf), brand_blocks(spark, sf)).select((F.round("trace", 4) + 0.0).alias("trace"))


@query(f"WITH {BLOCKED} SELECT r, s, arcs FROM bp")
def block_pair_counts(spark, sf):
    return metrics.block_pairs(part_graph(spark, sf), brand_blocks(spark, sf))


@query(f"WITH {BLOCKED} SELECT round(sum(arcs * ln(arcs / (CAST(x.vol AS DOUBLE) * y.vol))) / 2, 3) AS loglik FROM bp JOIN bs x ON x.block = bp.r JOIN bs y ON y.block = bp.s")
def sbm_loglik_by_brand(spark, sf):
    return metrics.sbm_loglik_df(part_graph(spark, sf), brand_blocks(spark, sf)).select(F.round("loglik", 3).alias("loglik"))


def segment_region(spark, sf):
    c = table(spark, sf, "customer").join(F.broadcast(table(spark, sf, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    truth = c.select(F.col("c_custkey").alias("id"), F.col("n_regionkey").cast("long").alias("block"))
    pred = c.select(F.col("c_custkey").alias("id"), F.col("c_nationkey").cast("long").alias("block"))
    return truth, pred


TABLE_SQL = "t AS (SELECT CAST(n_regionkey AS BIGINT) AS r, CAST(c_nationkey AS BIGINT) AS s, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2)"
PAIR_SQL = f"{TABLE_SQL}, p AS (SELECT (SELECT sum(n * (n - 1) / 2.0) FROM t) AS both_in, (SELECT sum(x * (x - 1) / 2.0) FROM (SELECT sum(n) AS x FROM t GROUP BY r)) AS truth, (SELECT sum(x * (x - 1) / 2.0) FROM (SELECT sum(n) AS x FROM t GROUP BY s)) AS pred, (SELECT sum(n) * (sum(n) - 1) / 2.0 FROM t) AS every)"


@query(f"WITH {TABLE_SQL} SELECT r, s, n FROM t")
def contingency_region_nation(spark, sf):
    return metrics.contingency(*segment_region(spark, sf))


@query(f"WITH {PAIR_SQL} SELECT round(both_in / pred, 6) AS precision, round(both_in / truth, 6) AS recall FROM p")
def pairwise_precision_recall(spark, sf):
    return metrics.pairwise_df(metrics.contingency(*segment_region(spark, sf))).select(F.round("precision", 6).alias("precision"), F.round("recall", 6).alias("recall"))


@query(f"WITH {PAIR_SQL} SELECT round((both_in - truth * pred / every) / ((truth + pred) / 2 - truth * pred / every), 6) AS ari FROM p")
def adjusted_rand(spark, sf):
    return metrics.pairwise_df(metrics.contingency(*segment_region(spark, sf))).select(F.round("ari", 6).alias("ari"))


@query(f"WITH {PAIR_SQL} SELECT round(2 * both_in / (truth + pred), 6) AS f1 FROM p")
def f1_score(spark, sf):
    return metrics.pairwise_df(metrics.contingency(*segment_region(spark, sf))).select(F.round("f1", 6).alias("f1"))


@query()
def accuracy_matched(spark, sf):
    return spark.createDataFrame([(metrics.accuracy(metrics.contingency(*segment_region(spark, sf))),)], "acc double")


# Split decisions for given halves: customers and suppliers of the bipartite graph, split by parity, within six sets.


def halves(spark, sf):
    g = graph.build(customer_supplier(spark, sf))
    return g, g.nodes.select("id", "deg", (F.col("id") % 3).cast("string").alias("path"), ((F.col("id") / 3).cast("long") % 2).cast("int").alias("side"))


HALF = f"{graph_ctes(CUSTOMER_SUPPLIER)}, h AS (SELECT id, deg, CAST(id % 3 AS VARCHAR) AS path, CAST((id // 3) % 2 AS INTEGER) AS side FROM deg), ie AS (SELECT x.path, x.side AS s0, y.side AS s1 FROM e JOIN h x ON x.id = e.src JOIN h y ON y.id = e.dst WHERE x.path = y.path), st AS (SELECT h.path, sum(1 - side) AS n0, sum(side) AS n1, sum((1 - side) * deg) AS vol0, sum(side * deg) AS vol1 FROM h GROUP BY h.path), ct AS (SELECT path, sum(CASE WHEN s0 <> s1 THEN 1 ELSE 0 END) AS cut, sum(CASE WHEN s0 = 0 AND s1 = 0 THEN 1 ELSE 0 END) AS in0, sum(CASE WHEN s0 = 1 AND s1 = 1 THEN 1 ELSE 0 END) AS in1 FROM ie GROUP BY path), x AS (SELECT st.path, n0, n1, vol0, vol1, coalesce(cut, 0) AS cut, coalesce(in0, 0) AS in0, coalesce(in1, 0) AS in1 FROM st LEFT JOIN ct ON st.path = ct.path)"


def half_stats(spark, sf):
    g, sided = halves(spark, sf)
    one, two = sided.select(F.col("id").alias("src"), F.col("path").alias("p0")), sided.select(F.col("id").alias("dst"), F.col("path").alias("p1"))
    edges = g.arcs.where("src < dst").select("src", "dst").join(one, "src").join(two, "dst").where("p0 = p1").select("src", "dst", F.col("p0").alias("path"))
    return g, selection.split_stats(sided, edges).drop("least0", "least1")


@query(f"WITH {HALF} SELECT path, CAST(n0 AS BIGINT) AS n0, CAST(n1 AS BIGINT) AS n1, CAST(cut AS BIGINT) AS cut, round(2.0 / (2 * m) * (CAST(vol0 AS DOUBLE) * vol1 / (2 * m) - cut), 9) + 0.0 AS gain FROM x CROSS JOIN tot")
def split_gain_given(spark, sf):
    g, stats = half_stats(spark, sf)
    total = float(2 * g.m)
    return stats.select("path", F.col("n0").cast("long").alias("n0"), F.col("n1").cast("long").alias("n1"), F.col("cut").cast("long").alias("cut"), (F.round(2 / F.lit(total) * (F.col("vol0").cast("double") * F.col("vol1") / total - F.col("cut")), 9) + 0.0).alias("gain"))


@query(
    f"WITH {HALF} SELECT path, CASE WHEN least(n0, n1) > 5 AND cut * 2 * m <= vol0 * vol1 THEN 'split' ELSE 'stop' END AS by_graph, CASE WHEN least(n0, n1) > 5 AND vol0 + vol1 > 0 AND cut * (vol0 + vol1) <= vol0 * vol1 THEN 'split' ELSE 'stop' END AS by_subset, CASE WHEN least(n0, n1) > 5 AND in0 + in1 + cut > 0 AND cut * 2 * (in0 + in1 + cut) <= (2 * in0 + cut) * (2 * in1 + cut) THEN 'split' ELSE 'stop' END AS by_induced FROM x CROSS JOIN tot"
)
def verdict_given(spark, sf):
    g, stats = half_stats(spark, sf)
    out = stats
    for scope in selection.SCOPES:
        out = selection.verdict(out, 2 * g.m, 5, scope).withColumnRenamed("verdict", f"by_{scope}")
    return out.select("path", "by_graph", "by_subset", "by_induced")


def scope_sql(vol: str, total: str) -> str:
    return f"WITH {HALF}, rows2 AS (SELECT h.path AS subset, h.side AS block, CAST(sum(deg) AS BIGINT) AS vol FROM h GROUP BY 1, 2), ea AS (SELECT path AS subset, block, CAST(sum(own) AS BIGINT) AS own, CAST(sum(a) AS BIGINT) AS arcs FROM (SELECT path, s0 AS block, CASE WHEN s0 = s1 THEN 1 ELSE 0 END AS own, 1 AS a FROM ie UNION ALL SELECT path, s1, CASE WHEN s0 = s1 THEN 1 ELSE 0 END, 1 FROM ie) q GROUP BY 1, 2), j AS (SELECT r.subset, r.vol, coalesce(own, 0) AS own, coalesce(arcs, 0) AS arcs FROM rows2 r LEFT JOIN ea USING (subset, block)), k AS (SELECT subset, {vol} AS v, own, CAST({total} AS DOUBLE) AS t FROM j) SELECT subset, round(sum(CASE WHEN t > 0 THEN own / t - (v / t) * (v / t) ELSE 0 END), 6) + 0.0 AS score, count(*) AS blocks FROM k GROUP BY subset"


def scored(spark, sf, scope):
    g, sided = halves(spark, sf)
    assign = sided.select("id", F.col("path").alias("subset"), F.col("side").alias("block"))
    return selection.local_modularity(g, assign, scope).select("subset", (F.round("score", 6) + 0.0).alias("score"), "blocks")


@query(scope_sql("vol", "2 * (SELECT m FROM tot)"))
def local_modularity_graph(spark, sf):
    return scored(spark, sf, "graph")


@query(scope_sql("vol", "sum(vol) OVER (PARTITION BY subset)"))
def local_modularity_subset(spark, sf):
    return scored(spark, sf, "subset")


@query(scope_sql("arcs", "sum(arcs) OVER (PARTITION BY subset)"))
def local_modularity_induced(spark, sf):
    return scored(spark, sf, "induced")


CENTRES = "c AS (SELECT label AS path, min_by(embedding, vec_id) AS c0, max_by(embedding, vec_id) AS c1 FROM embeddings GROUP BY label)"
DISTANCE = "list_sum(list_transform(list_zip(e.embedding, {c}), lambda p: (CAST(p[1] AS DOUBLE) - CAST(p[2] AS DOUBLE)) * (CAST(p[1] AS DOUBLE) - CAST(p[2] AS DOUBLE))))"


def given_centres(spark, sf):
    rows = table(spark, sf, "embeddings").select(F.col("label").cast("string").alias("path"), F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    return rows, rows.groupBy("path").agg(F.min_by("v", "id").alias("c0"), F.max_by("v", "id").alias("c1"))


@query(f"WITH {CENTRES} SELECT vec_id AS id, CAST(label AS VARCHAR) AS path, CASE WHEN {DISTANCE.format(c='c.c1')} < {DISTANCE.format(c='c.c0')} THEN 1 ELSE 0 END AS side FROM embeddings e JOIN c ON c.path = e.label")
def nearest_centroid_given(spark, sf):
    rows, centres = given_centres(spark, sf)
    d0, d1 = (F.aggregate(F.zip_with("v", c, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x) for c in ("c0", "c1"))
    return rows.join(F.broadcast(centres), "path").select("id", "path", (d1 < d0).cast("int").alias("side"))


@query(
    f"WITH {CENTRES}, s AS (SELECT CAST(label AS VARCHAR) AS path, vec_id, embedding, CASE WHEN {DISTANCE.format(c='c.c1')} < {DISTANCE.format(c='c.c0')} THEN 1 ELSE 0 END AS side FROM embeddings e JOIN c ON c.path = e.label) SELECT path, side, count(*) AS n, round(avg(CAST(embedding[1] AS DOUBLE)), 6) + 0.0 AS first, round(avg(CAST(embedding[64] AS DOUBLE)), 6) + 0.0 AS last FROM s GROUP BY path, side"
)
def lloyd_step_given(spark, sf):
    from ..operators.bisect import lloyd_step

    rows, centres = given_centres(spark, sf)
    out = lloyd_step(rows, centres, 64)
    return out.select("path", "side", "n", (F.round(F.col("centre")[0], 6) + 0.0).alias("first"), (F.round(F.col("centre")[63], 6) + 0.0).alias("last"))


# The generator's arithmetic on customers in nations.


def nation_params(spark, sf, ratio=2.5, seed=SEED):
    nodes = table(spark, sf, "customer").select(F.col("c_custkey").alias("id"), F.col("c_nationkey").alias("b"))
    return generator.benchmark_params(nodes, ratio=ratio, mean_degree=30.0, seed=seed, block="b", simple=False)


A, B = generator.THETA_LOW ** (1 - generator.THETA_POWER), generator.THETA_HIGH ** (1 - generator.THETA_POWER)
THETA_SQL = f"(pow({A!r} + {hash01_sql(SEED, 'c_custkey', '7')} * {B - A!r}, {1 / (1 - generator.THETA_POWER)!r}) / {generator.theta_mean()!r})"
NODES_SQL = f"np AS (SELECT c_custkey AS id, c_nationkey AS block, {THETA_SQL} AS theta FROM customer)"
SOLVE_SQL = f"{NODES_SQL}, sums AS (SELECT block, count(*) AS n, sum(theta) AS t, sum(theta * theta) AS q FROM np GROUP BY block), w AS (SELECT sum(n) * 15.0 / 3.5 / ((sum(t) * sum(t) - sum(t * t)) / 2) AS across, sum(n) * 15.0 * 2.5 / 3.5 / sum(t) AS within FROM sums), bsum AS (SELECT block, n, t, q, within * t / ((t * t - q) / 2) AS inside FROM sums CROSS JOIN w), npi AS (SELECT np.*, inside FROM np JOIN bsum USING (block))"


@query(f"WITH {NODES_SQL} SELECT id, block, round(theta, 9) AS theta FROM np")
def benchmark_params(spark, sf):
    return nation_params(spark, sf).nodes.select("id", "block", F.round("theta", 9).alias("theta"))


@query(f"WITH {SOLVE_SQL} SELECT x.block AS r, y.block AS s, CAST(CASE WHEN x.block = y.block THEN x.n * (x.n - 1) / 2 ELSE x.n * y.n END AS BIGINT) AS cells, round(CASE WHEN x.block = y.block THEN (x.t * x.t - x.q) / 2 * x.inside ELSE x.t * y.t * across END, 6) AS mass FROM bsum x JOIN bsum y ON x.block <= y.block CROSS JOIN w")
def rates_block_pairs(spark, sf):
    return generator.rates_df(nation_params(spark, sf)).select("r", "s", "cells", F.round("mass", 6).alias("mass"))


@query(f"WITH {NODES_SQL} SELECT block, CAST(row_number() OVER (PARTITION BY block ORDER BY id) - 1 AS INTEGER) AS pos, id, round(sum(theta) OVER (PARTITION BY block ORDER BY id ROWS UNBOUNDED PRECEDING), 6) AS upto FROM np")
def theta_prefix(spark, sf):
    return generator.prefix(nation_params(spark, sf)).select("block", "pos", "id", F.round("upto", 6).alias("upto"))


@query(f"WITH {SOLVE_SQL} SELECT x.id, y.block AS s, round(sum(CASE WHEN x.block = y.block THEN x.inside ELSE across END * x.theta * y.theta), 6) AS row_mass FROM npi x JOIN npi y ON x.block < y.block OR (x.block = y.block AND y.id > x.id) CROSS JOIN w GROUP BY x.id, y.block")
def range_sum_cells(spark, sf):
    """The summed rate of each node's row in the table of cells of each block pair, from prefix sums; the SQL adds up cells."""
    p = nation_params(spark, sf)
    rows = generator.prefix(p)
    whole = rows.groupBy(F.col("block").alias("s")).agg(F.sum("theta").alias("whole"), F.count(F.lit(1)).alias("n"))
    rate = p.omega_df().select(F.col("r").alias("block"), "s", "rate")
    cells = rows.join(F.broadcast(rate), "block").join(F.broadcast(whole), "s")
    same = F.col("block") == F.col("s")
    mass = F.col("rate") * F.col("theta") * (F.col("whole") - F.when(same, F.col("upto")).otherwise(0.0))
    return cells.where(~same | (F.col("pos") < F.col("n") - 1)).select("id", "s", F.round(mass, 6).alias("row_mass"))


CELLS_SQL = f"WITH {SOLVE_SQL} SELECT x.id AS src, y.id AS dst FROM npi x JOIN npi y ON x.id < y.id CROSS JOIN w WHERE {hash01_sql(SEED, 'x.id', 'y.id')} < 1 - exp(-x.theta * y.theta * CASE WHEN x.block = y.block THEN x.inside ELSE across END)"


@query(CELLS_SQL)
def planted_cells(spark, sf):
    return generator.cells(nation_params(spark, sf), SEED, 20_000)


@query(f"WITH {SOLVE_SQL}, c AS (SELECT least(x.block, y.block) AS r, greatest(x.block, y.block) AS s, 1 - exp(-x.theta * y.theta * CASE WHEN x.block = y.block THEN x.inside ELSE across END) AS p FROM npi x JOIN npi y ON x.id < y.id CROSS JOIN w) SELECT r, s, count(*) AS cells, round(sum(p), 4) AS expected FROM c GROUP BY r, s")
def planted_expected_edges(spark, sf):
    """Expected simple edges of all block pairs, cell by cell."""
    p = nation_params(spark, sf)
    one, two = p.nodes.select("id", F.col("block").alias("b0"), F.col("theta").alias("t0")), p.nodes.select(F.col("id").alias("j"), F.col("block").alias("b1"), F.col("theta").alias("t1"))
    cells = one.join(two, F.col("j") > F.col("id")).withColumn("lo", F.least("b0", "b1")).withColumn("hi", F.greatest("b0", "b1")).join(F.broadcast(p.omega_df()), (F.col("lo") == F.col("r")) & (F.col("hi") == F.col("s")))
    return cells.groupBy("r", "s").agg(F.count(F.lit(1)).alias("cells"), F.round(F.sum(1 - F.exp(-F.col("t0") * F.col("t1") * F.col("rate"))), 4).alias("expected"))


@query(f"SELECT c_custkey AS id, {hash01_sql(SEED, 'c_custkey', '0')} AS u, round({gauss_sql(SEED, 'c_custkey', '0')}, 9) AS g FROM customer")
def op_box_muller(spark, sf):
    from ..functions.rng import gauss

    return table(spark, sf, "customer").select(F.col("c_custkey").alias("id"), hash01(SEED, F.col("c_custkey"), 0).alias("u"), F.round(gauss(SEED, F.col("c_custkey"), 0), 9).alias("g"))


