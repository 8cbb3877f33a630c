"""The complete graph in closed form, and suppliers whose graph is not complete."""

import numpy as np
from pyspark.sql import functions as F

from blockfinder import queries
from blockfinder.operators import complete, features, gnn, graph
from blockfinder.plans.pipeline import partition

queries.load_all()


def test_as_the_listed_graph(spark):
    g = graph.build(spark.createDataFrame([(3 * a, 3 * b) for a in range(30) for b in range(a)], "a long, b long"))
    own = complete.graph_of(g.nodes)
    assert (own.n, own.m, {r["deg"] for r in own.nodes.collect()}) == (30, g.m, {29})
    listed = {r["id"]: r["v"] for r in gnn.forward(g, features.project(g, "cut", 16), (16, 8, 8)).collect()}
    closed = {r["id"]: r["v"] for r in complete.embed(own, (16, 8, 8)).collect()}
    assert listed.keys() == closed.keys() and max(np.abs(np.subtract(listed[k], closed[k])).max() for k in listed) < 1e-4
    blocks = lambda df: sorted((r["id"], r["block"]) for r in df.collect())
    assert blocks(partition(g, "cut", (16, 8)).blocks) == blocks(complete.partition(g.nodes, (16, 8)))


def test_suppliers_in_parts_that_share_no_order(spark, tmp_path):
    rows = [(part * 100 + o, part * 1000 + s) for part in range(3) for o in range(40) for s in ((o * 3) % 12, (o * 5 + 1) % 12)]
    rows += [(9000, 77_777), (9001, None), (9001, 5)]  # alone in their orders
    spark.createDataFrame(rows, "l_orderkey long, l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    ends = {s for part in range(3) for o in range(40) for pair in [((o * 3) % 12, (o * 5 + 1) % 12)] if pair[0] != pair[1] for s in (part * 1000 + pair[0], part * 1000 + pair[1])}
    found = queries.QUERIES["partition_complete_supplier"](spark, str(tmp_path)).collect()
    assert sorted((r["id"], r["block"]) for r in found) == [(k, min(ends)) for k in sorted(ends)]
