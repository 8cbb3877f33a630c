"""Hierarchical model selection: recursive bisection that a local modularity score stops.

All open sets of a level are handled in one job. A set that one task can hold is finished there, with all its levels.
Whether a split stays is decided in whole numbers: with volumes a and b of the halves, c edges between them and S the
total volume of the scope, it stays if c * S <= a * b, and if both halves have over ``eps`` nodes.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.state import dropped, placed as put, written
from . import bisect
from .graph import Graph

SCOPES = ("graph", "subset", "induced")
LOCAL_NODES = bisect.ONE_TASK_ROWS
LOCAL_EDGES = 8_000_000
OPEN_AT_ONCE = 4_096  # sets in a job; what the driver holds of each is its plane
TREE = "path string, parent string, n long, vol long, m_in long, cut long, verdict string, w array<double>, b double"


def parts_of(arcs: DataFrame, assign: DataFrame) -> DataFrame:
    """For each set of ``assign`` (id, block): n, volume in the graph and edges inside."""
    one, two = (assign.select(F.col("id").alias(e), F.col("block").alias(f"b_{e}")) for e in ("src", "dst"))
    inside = arcs.where("src < dst").join(one, "src").join(two, "dst").where("b_src = b_dst").groupBy(F.col("b_src").alias("block")).agg(F.count(F.lit(1)).alias("m_in"))
    return inside


def local_modularity(g: Graph, assign: DataFrame, null_scope: str = "graph") -> DataFrame:
    """(subset, score, blocks) of a division ``assign`` (id, subset, block) of each subset into blocks.

    ``graph``: degrees and edge count of the whole graph. ``subset``: e is half the subset's volume. ``induced``: the
    usual modularity of the subset's own graph.
    """
    if null_scope not in SCOPES:
        raise ValueError(f"null_scope must be one of {SCOPES}")
    one, two = (assign.select(F.col("id").alias(e), F.col("subset").alias(f"s_{e}"), F.col("block").alias(f"b_{e}")) for e in ("src", "dst"))
    inside = g.arcs.select("src", "dst").join(one, "src").join(two, "dst").where("s_src = s_dst")
    edges = inside.groupBy(F.col("s_src").alias("subset"), F.col("b_src").alias("block")).agg(F.sum((F.col("b_src") == F.col("b_dst")).cast("long")).alias("own"), F.count(F.lit(1)).alias("arcs"))
    sizes = g.nodes.join(assign, "id").groupBy("subset", "block").agg(F.sum("deg").alias("vol"))
    rows = sizes.join(edges, ["subset", "block"], "left").select("subset", "block", "vol", F.coalesce("own", F.lit(0)).alias("own"), F.coalesce("arcs", F.lit(0)).alias("arcs"))
    vol = F.col("arcs" if null_scope == "induced" else "vol")
    total = {"graph": F.lit(2 * g.m), "subset": F.sum("vol").over(W_SUBSET()), "induced": F.sum("arcs").over(W_SUBSET())}[null_scope]
    term = rows.withColumn("total", total.cast("double")).withColumn("term", F.when(F.col("total") > 0, F.col("own") / F.col("total") - (vol / F.col("total")) * (vol / F.col("total"))).otherwise(0.0))
    return term.groupBy("subset").agg(F.sum("term").alias("score"), F.count(F.lit(1)).alias("blocks"))


def W_SUBSET():
    from pyspark.sql import Window

    return Window.partitionBy("subset")


def split_stats(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(path, n0, n1, vol0, vol1, cut, in0, in1) from ``nodes`` (id, deg, path, side) and inner ``edges`` (src, dst, path)."""
    side = F.col("side")
    sums = nodes.groupBy("path").agg(
        F.sum(1 - side).alias("n0"), F.sum(side).alias("n1"), F.sum((1 - side) * F.col("deg")).alias("vol0"), F.sum(side * F.col("deg")).alias("vol1"), F.min(F.when(side == 0, F.col("id"))).alias("least0"), F.min(F.when(side == 1, F.col("id"))).alias("least1")
    )
    ends = with_sides(edges, nodes)
    cuts = ends.groupBy("path").agg(F.sum((F.col("s0") != F.col("s1")).cast("long")).alias("cut"), F.sum(((F.col("s0") == 0) & (F.col("s1") == 0)).cast("long")).alias("in0"), F.sum(((F.col("s0") == 1) & (F.col("s1") == 1)).cast("long")).alias("in1"))
    zero = [F.coalesce(c, F.lit(0)).alias(c) for c in ("cut", "in0", "in1")]
    return sums.join(cuts, "path", "left").select(*sums.columns, *zero)


def with_sides(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    one, two = (nodes.select(F.col("id").alias(e), F.col("side").alias(s)) for e, s in (("src", "s0"), ("dst", "s1")))
    return edges.join(one, "src").join(two, "dst")


def stays(n0: int, n1: int, vol0: int, vol1: int, cut: int, in0: int, in1: int, total: int, eps: int, null_scope: str) -> bool:
    """Whether a split is kept."""
    if min(n0, n1) <= eps:
        return False
    if null_scope == "induced":
        vol0, vol1 = 2 * in0 + cut, 2 * in1 + cut
    scope = total if null_scope == "graph" else vol0 + vol1
    return scope > 0 and cut * scope <= vol0 * vol1


def verdict(stats: DataFrame, total: int, eps: int = 5, null_scope: str = "graph") -> DataFrame:
    """``stats`` with ``verdict``: split or stop. Products are decimals, so that no volume overflows."""
    wide = {c: F.col(c).cast("decimal(19,0)") for c in ("vol0", "vol1", "cut", "in0", "in1")}
    if null_scope == "induced":
        wide["vol0"], wide["vol1"] = 2 * wide["in0"] + wide["cut"], 2 * wide["in1"] + wide["cut"]
    scope = F.lit(total).cast("decimal(19,0)") if null_scope == "graph" else wide["vol0"] + wide["vol1"]
    split = (F.least("n0", "n1") > eps) & (scope > 0) & (wide["cut"] * scope <= wide["vol0"] * wide["vol1"])
    return stats.withColumn("verdict", F.when(split, "split").otherwise("stop"))


def finish(ids: np.ndarray, deg: np.ndarray, z: np.ndarray, a: np.ndarray, b: np.ndarray, root: str, total: int, eps: int, null_scope: str, max_depth: int, how: dict) -> tuple[list[str], list[tuple]]:
    """The whole recursion of one set in memory. a, b: places of the ends of its inner edges. Gives each node's leaf and the tree."""
    leaf = np.empty(len(ids), object)
    tree, work = [], [(np.arange(len(ids)), np.arange(len(a)), root)]
    side_of = np.zeros(len(ids), bool)
    while work:
        own, edges, path = work.pop()
        w, shift = bisect.fit(z[own], ids[own], **how)
        side = z[own].astype("f8") @ w > shift
        if side.any() and not side.all() and ids[own][side].min() < ids[own][~side].min():
            side, w, shift = ~side, -w, -shift
        side_of[own] = side
        s, t = side_of[a[edges]], side_of[b[edges]]
        n1, vol, vol1 = int(side.sum()), int(deg[own].sum()), int(deg[own][side].sum())
        cut, in1 = int((s != t).sum()), int((s & t).sum())
        split = len(path) < max_depth and stays(len(own) - n1, n1, vol - vol1, vol1, cut, len(edges) - cut - in1, in1, total, eps, null_scope)
        tree.append((path, path[:-1] if path else None, len(own), vol, len(edges), cut, "split" if split else "stop", w.tolist(), shift))
        if split:
            work += [(own[side], edges[s & t], path + "1"), (own[~side], edges[~s & ~t], path + "0")]
        else:
            leaf[own] = path
    return leaf.tolist(), tree


def finish_sets(nodes: DataFrame, edges: DataFrame, total: int, eps: int, null_scope: str, max_depth: int, how: dict) -> DataFrame:
    """Finish each set of ``nodes`` (id, deg, v, path) with inner ``edges`` (src, dst, path) in a task of its own.

    Rows with an id give the leaf of a node; rows without give the tree.
    """
    columns = ["n", "vol", "m_in", "cut", "verdict", "w", "b"]
    kinds = [pa.int64()] * 4 + [pa.string(), pa.list_(pa.float64()), pa.float64()]

    def one(key, left, right):
        v = left["v"].combine_chunks()
        ids = left["id"].to_numpy()
        order = np.argsort(ids)
        ids, deg, z = ids[order], left["deg"].to_numpy()[order], v.flatten().to_numpy(zero_copy_only=False).reshape(len(v), -1)[order]
        a, b = (np.searchsorted(ids, right[c].to_numpy()) for c in ("src", "dst"))
        leaf, tree = finish(ids, deg, z, a, b, key[0].as_py(), total, eps, null_scope, max_depth, how)
        cells = list(zip(*tree, strict=True))
        none = len(leaf)
        return pa.table(
            {"id": pa.array([*ids.tolist(), *[None] * len(tree)], pa.int64()), "path": pa.array([*leaf, *cells[0]]), "parent": pa.array([None] * none + list(cells[1]), pa.string())}
            | {c: pa.array([None] * none + list(x), k) for c, x, k in zip(columns, cells[2:], kinds, strict=True)}
        )

    return nodes.groupBy("path").cogroup(edges.groupBy("path")).applyInArrow(one, f"id long, {TREE}")


def hierarchical(
    g: Graph, z: DataFrame, eps: int = 5, null_scope: str = "graph", max_depth: int | None = None, local_below: int = LOCAL_NODES, max_iter: int = 100, n_init: int = 1, init: str = "axis", seed: int = 0, isolates: str = "bucket", **how
) -> tuple[DataFrame, DataFrame]:
    """Blocks (id, block) and tree of ``z`` (id, v). A block's name is its least id.

    Sets of at most ``local_below`` nodes (and ``LOCAL_EDGES`` inner edges) are finished in a task each; larger ones are
    split level by level, each step a job over all of them. Both go by the same planes, so the limit does not change
    the blocks. Nodes without edges are one block of their own (``bucket``) or each one (``singleton``), never part of a
    split.
    """
    if null_scope not in SCOPES:
        raise ValueError(f"null_scope must be one of {SCOPES}")
    how |= {"max_iter": max_iter, "n_init": n_init, "init": init, "seed": seed}
    total, spark = 2 * g.m, g.nodes.sparkSession
    max_depth = max_depth or 4 * max(4, math.ceil(math.log2(max(2, g.n))))
    nodes = z.select("id", "v").join(g.nodes.where("deg > 0"), "id").select("id", "deg", F.col("v").cast("array<float>").alias("v"), F.lit("").alias("path"))
    edges = g.arcs.where("src < dst").select("src", "dst", F.lit("").alias("path"))
    leaves: list[DataFrame] = []
    trees: list[DataFrame] = []
    held: list[str] = []  # folders of this level's rows: deleted when the next level's are written
    if g.n > local_below:
        nodes, folder = put(nodes)
        held.append(folder)
    sizes = {"": (nodes.count(), g.m)} if g.m else {}
    while sizes:
        small = {p for p, (n, m) in sizes.items() if n <= local_below and m <= LOCAL_EDGES}
        if small:
            here = nodes if len(small) == len(sizes) else of_sets(nodes, small)
            done = written(finish_sets(here, edges if here is nodes else of_sets(edges, small), total, eps, null_scope, max_depth, how))
            leaves.append(done.where("id is not null").select("id", "path"))
            trees.append(done.where("id is null").drop("id"))
            if here is nodes:
                break
        open_sets = sorted(set(sizes) - small)
        next_nodes, next_edges, sizes_now = [], [], sizes
        sizes, next_held = {}, []
        for at in range(0, len(open_sets), OPEN_AT_ONCE):
            wave = open_sets[at : at + OPEN_AT_ONCE]
            wave_nodes, wave_edges = (nodes, edges) if len(wave) == len(sizes_now) else (of_sets(nodes, wave), of_sets(edges, wave))
            planes = bisect.two_means(wave_nodes, {p: sizes_now[p][0] for p in wave}, **how)
            sided, sided_folder = put(bisect.assign_side(wave_nodes, planes))
            if len(wave) == len(sizes_now) and nodes is wave_nodes and held:
                dropped(spark, held.pop(0))  # the rows are all in ``sided``
            stats = {r["path"]: r for r in split_stats(sided, wave_edges).collect()}
            facts, going = [], []
            for p, r in stats.items():
                keep = len(p) < max_depth and stays(*[r[c] for c in ("n0", "n1", "vol0", "vol1", "cut", "in0", "in1")], total, eps, null_scope)
                # The half with the least id is called 0.
                turned = r["least0"] is not None and r["least1"] is not None and r["least1"] < r["least0"]
                w, b = planes[p]
                facts.append((p, p[:-1] if p else None, r["n0"] + r["n1"], r["vol0"] + r["vol1"], r["in0"] + r["in1"] + r["cut"], r["cut"], "split" if keep else "stop", (-w if turned else w).tolist(), -b if turned else b))
                if keep:
                    going.append((p, turned))
                    halves = ((r["n0"], r["in0"]), (r["n1"], r["in1"]))
                    sizes[p + "0"], sizes[p + "1"] = halves[::-1] if turned else halves
            trees.append(written(spark.createDataFrame(facts, TREE)))
            ways = F.broadcast(spark.createDataFrame(going, "path string, turned boolean"))
            marked = sided.join(ways, "path", "left")
            leaves.append(written(marked.where("turned is null").select("id", "path")))
            side = F.when(F.col("turned"), 1 - F.col("side")).otherwise(F.col("side"))
            placed = marked.where("turned is not null").select("id", "deg", "v", F.concat("path", side.cast("string")).alias("path"))
            rows, folder = put(placed)
            next_nodes.append(rows)
            next_held.append(folder)
            dropped(spark, sided_folder)
            one, two = (next_nodes[-1].select(F.col("id").alias(e), F.col("path").alias(p)) for e, p in (("src", "p"), ("dst", "q")))
            inner, folder = put(wave_edges.select("src", "dst").join(one, "src").join(two, "dst").where("p = q").select("src", "dst", F.col("p").alias("path")))
            next_edges.append(inner)
            next_held.append(folder)
        dropped(spark, *held)
        held = next_held
        nodes, edges = reduce(DataFrame.unionByName, next_nodes), reduce(DataFrame.unionByName, next_edges)
    dropped(spark, *held)
    alone = g.nodes.where("deg = 0").select("id", (F.concat(F.lit("isolated"), F.col("id").cast("string")) if isolates == "singleton" else F.lit("isolated")).alias("path"))
    placed = alone
    for part in leaves:
        placed = placed.unionByName(part)
    return written(label(placed)), union_all(g, trees)


def of_sets(rows: DataFrame, paths) -> DataFrame:
    """The rows of the sets with these paths."""
    return rows.join(F.broadcast(rows.sparkSession.createDataFrame([(p,) for p in paths], "path string")), "path", "left_semi").select(rows.columns)


def union_all(g: Graph, trees: list[DataFrame]) -> DataFrame:
    out = g.nodes.sparkSession.createDataFrame([], TREE)
    for t in trees:
        out = out.unionByName(t)
    return written(out)


def label(placed: DataFrame) -> DataFrame:
    """(id, block, path) of (id, path): a leaf's block is its least id."""
    least = placed.groupBy("path").agg(F.min("id").alias("block"))
    return placed.join(least, "path").select("id", "block", "path")
