"""Random features: a structure matrix times a Gaussian matrix that exists only as a function of (seed, node, column)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.rng import gauss, gauss_block
from .graph import Graph
from .kernels import hub_salt, matrix, reduce_arcs, vectors

KINDS = ("cut", "mod", "mod_full")
CELLS_AT_ONCE = 1 << 16


def structure(g: Graph, kind: str = "cut") -> DataFrame:
    """arcs with ``w``, the structure matrix on edges: 1/sqrt(d d') for ``cut``, 1 - d d'/(2m) for ``mod``."""
    return g.arcs.withColumn("w", weight(kind, F.lit(float(2 * g.m))))


def weight(kind: str, total: Column) -> Column:
    product = F.col("dsrc").cast("double") * F.col("ddst")
    if kind == "cut":
        return 1 / F.sqrt(product)
    if kind in ("mod", "mod_full"):
        return 1 - product / total
    raise ValueError(f"kind must be one of {KINDS}")


def spread(width: int, scale: str) -> float:
    """The Gaussian's standard deviation: ``width ** -0.5``, or its square root where that is read as a variance."""
    return width**-0.5 if scale == "std" else width**-0.25


def project(g: Graph, kind: str = "cut", width: int = 64, seed: int = 0, scale: str = "std", salt: int | None = None) -> DataFrame:
    """(id, v): the features of all nodes; nodes without edges have zeros. No vector is shuffled.

    ``mod_full`` is the dense modularity matrix: its rank-one part needs one more sum over all nodes. ``salt``: parts
    that a node's arcs are dealt into, by default as many as the largest degree asks for.
    """
    if kind not in KINDS:
        raise ValueError(f"kind must be one of {KINDS}")
    std, total = spread(width, scale), float(max(1, 2 * g.m))

    def cut(dst, dsrc, ddst):
        return gauss_block(seed, dst, width) * (std / np.sqrt(dsrc.astype("f8") * ddst))[:, None].astype("f4")

    def mod(dst, dsrc, ddst):
        return gauss_block(seed, dst, width) * (std * (1 - dsrc.astype("f8") * ddst / total))[:, None].astype("f4")

    def plain(dst, dsrc, ddst):
        return gauss_block(seed, dst, width) * np.float32(std)

    out = reduce_arcs(g.arcs, ["dst", "dsrc", "ddst"], width, {"cut": cut, "mod": mod, "mod_full": plain}[kind], salt or hub_salt(g))
    if kind == "mod_full":
        lift = weighted_sum(g, width, seed) * std / total
        out = without_rank_one(g.nodes.join(out, "id", "left"), lift, width)
    return with_all_nodes(g, out, width)


def with_all_nodes(g: Graph, v: DataFrame, width: int) -> DataFrame:
    zero = F.array_repeat(F.lit(0.0).cast("float"), width)
    return g.nodes.join(v.select("id", "v"), "id", "left").select("id", F.coalesce("v", zero).alias("v"))


def weighted_sum(g: Graph, width: int, seed: int) -> np.ndarray:
    """The sum over nodes of degree times Gaussian row: one vector."""
    import pyarrow as pa

    def run(batches):
        total = np.zeros(width)
        for b in batches:
            total += b.column(1).to_numpy().astype("f8") @ gauss_block(seed, b.column(0).to_numpy(), width).astype("f8")
        yield pa.RecordBatch.from_arrays([pa.array(range(width), pa.int64()), pa.array(total)], ["dim", "x"])

    parts = g.nodes.select("id", "deg").mapInArrow(run, "dim long, x double").groupBy("dim").agg(F.sum("x").alias("x")).collect()
    return np.array([r["x"] for r in sorted(parts, key=lambda r: r["dim"])])


def without_rank_one(nodes: DataFrame, lift: np.ndarray, width: int) -> DataFrame:
    import pyarrow as pa

    def run(batches):
        for b in batches:
            has = b.column(2).is_valid().to_numpy(zero_copy_only=False)
            rows = np.zeros((b.num_rows, width))
            if has.any():
                rows[has] = matrix(b.column(2).drop_null(), width)
            rows -= b.column(1).to_numpy().astype("f8")[:, None] * lift
            yield pa.RecordBatch.from_arrays([b.column(0), vectors(rows)], ["id", "v"])

    return nodes.select("id", "deg", "v").mapInArrow(run, "id long, v array<float>")


def dense_modularity(g: Graph) -> DataFrame:
    """(src, dst, q): all cells of the modularity matrix. Rows are made where a node's neighbours are; no cell is shuffled."""
    import pyarrow as pa

    table = g.nodes.select("id", "deg").toArrow().sort_by("id")
    shared = g.nodes.sparkSession.sparkContext.broadcast((table["id"].to_numpy(), table["deg"].to_numpy().astype("f8")))
    total = float(2 * g.m)

    def run(batches):
        ids, deg = shared.value
        for b in batches:
            near = b.column(2)
            for k in range(b.num_rows):
                row = np.zeros(len(ids))
                row[np.searchsorted(ids, near[k].values.to_numpy())] = 1
                q = row - float(b.column(1)[k].as_py()) * deg / total
                for at in range(0, len(ids), CELLS_AT_ONCE):
                    part = slice(at, at + CELLS_AT_ONCE)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids[part]), b.column(0)[k].as_py(), "i8")), pa.array(ids[part]), pa.array(q[part])], ["src", "dst", "q"])

    rows = g.arcs.groupBy("src").agg(F.first("dsrc").alias("deg"), F.collect_list("dst").alias("near"))
    alone = g.nodes.where("deg = 0").select(F.col("id").alias("src"), "deg", F.array().cast("array<bigint>").alias("near"))
    return rows.unionByName(alone).mapInArrow(run, "src long, dst long, q double")


def factored(g: Graph, kind: str = "mod", width: int = 64, seed: int = 0, scale: str = "std") -> DataFrame:
    """What updates need: (id, deg, p1, p2) with Y = p1 - deg/(2m) p2 for ``mod``, Y = p1/sqrt(deg) for ``cut``.

    p1 sums the neighbours' Gaussian rows (over the root of their degree for ``cut``), p2 these times the degree.
    """
    std = np.float32(spread(width, scale))

    def one(dst, ddst):
        rows = gauss_block(seed, dst, width) * std
        return rows if kind == "mod" else rows / np.sqrt(ddst.astype("f8"))[:, None].astype("f4")

    def two(dst, ddst):
        return gauss_block(seed, dst, width) * (std * ddst.astype("f4"))[:, None]

    p1 = reduce_arcs(g.arcs, ["dst", "ddst"], width, one).withColumnRenamed("v", "p1")
    if kind == "cut":
        return g.nodes.join(p1, "id").select("id", "deg", "p1", F.lit(None).cast("array<float>").alias("p2"))
    p2 = reduce_arcs(g.arcs, ["dst", "ddst"], width, two).withColumnRenamed("v", "p2")
    return g.nodes.join(p1, "id").join(p2, "id").select("id", "deg", "p1", "p2")


def from_factors(factors: DataFrame, kind: str, total: int) -> DataFrame:
    """(id, v) from factors; ``total`` is twice the number of edges."""
    if kind == "cut":
        v = F.transform("p1", lambda x: x / F.sqrt(F.col("deg").cast("double")))
    else:
        v = F.zip_with("p1", "p2", lambda x, y: x - F.col("deg") / F.lit(float(total)) * y)
    return factors.select("id", v.cast("array<float>").alias("v"))


def project_long(g: Graph, kind: str, width: int, seed: int) -> DataFrame:
    """(id, dim, val) in DataFrame functions alone, with the Gaussian that SQL engines share."""
    dims = F.explode(F.sequence(F.lit(0), F.lit(width - 1))).alias("dim")
    parts = structure(g, kind).select("src", "dst", "w", dims)
    return parts.groupBy(F.col("src").alias("id"), "dim").agg(F.sum(F.col("w") * gauss(seed, F.col("dst"), F.col("dim")) * width**-0.5).alias("val"))


def project_through(g: Graph, kind: str, width: int, seed: int) -> DataFrame:
    """Without random features: the structure matrix itself goes into the first layer, whose weights are then one
    Gaussian row for each node. Associativity makes that a projection; nothing of nodes times nodes is ever made."""
    return project(g, kind, width, seed)
