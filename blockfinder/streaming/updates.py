"""Updates of degrees, features, embeddings and the tree when edges are added.

The cut variant's features change wherever a neighbour's degree does, one step from the ends of new edges; each layer
adds a step. ``mode="ball"`` rewrites every node whose vector can have changed and equals a full run; ``"touched"``
rewrites the ends of new edges only, which is cheaper and approximate.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import features, gnn, graph, selection
from ..operators.graph import Graph
from ..plans.state import settle


@dataclass(frozen=True)
class State:
    """What is carried from batch to batch: the graph, the last embedding (id, deg, v), blocks (id, block, path) and the tree."""

    graph: Graph
    embedding: DataFrame
    blocks: DataFrame
    tree: DataFrame
    kind: str
    layers: tuple[int, ...]
    seed: int
    eps: int


def new_edges(edges: DataFrame, batch: DataFrame) -> DataFrame:
    """The edges of a batch (a, b) that are not known yet; a batch that comes twice adds nothing."""
    return graph.canonical(batch).join(edges.select("src", "dst"), ["src", "dst"], "left_anti")


def degree_delta(deg: DataFrame, added: DataFrame) -> DataFrame:
    """(id, deg) after ``added`` (src, dst): known nodes' degrees grow, new nodes appear."""
    more = graph.degrees(graph.both_ways(added)).withColumnRenamed("deg", "more")
    return deg.join(more, "id", "full_outer").select("id", (F.coalesce("deg", F.lit(0)) + F.coalesce("more", F.lit(0))).alias("deg"))


def grow(g: Graph, added: DataFrame) -> Graph:
    """The graph with new edges: degrees by their delta, arcs with the new degrees of both ends."""
    nodes = settle(degree_delta(g.nodes, added))
    arcs = g.arcs.select("src", "dst").unionByName(graph.both_ways(added))
    return Graph(nodes, settle(graph.with_degrees(arcs, nodes)), nodes.count(), g.m + added.count())


def feature_delta(factors: DataFrame, before: Graph, after: Graph, added: DataFrame, width: int, seed: int) -> DataFrame:
    """Factors (id, deg, p1, p2) of the modularity variant after ``added``, from those before.

    p1 and p2 get the new neighbours' terms, and p2 the change of degree of every old neighbour whose degree grew; only
    arcs of new edges and old arcs into touched nodes are read.
    """
    from ..operators.kernels import reduce_arcs, sum_vectors
    from ..functions.rng import gauss_block

    std = np.float32(features.spread(width, "std"))
    fresh = graph.with_degrees(graph.both_ways(added), after.nodes)
    one = reduce_arcs(fresh, ["dst"], width, lambda dst: gauss_block(seed, dst, width) * std)
    two = reduce_arcs(fresh, ["dst", "ddst"], width, lambda dst, ddst: gauss_block(seed, dst, width) * (std * ddst.astype("f4"))[:, None])
    grown = after.nodes.join(before.nodes.withColumnRenamed("deg", "old"), "id").where("deg > old").select(F.col("id").alias("dst"), (F.col("deg") - F.col("old")).alias("more"))
    old = before.arcs.select("src", "dst").join(grown, "dst")
    shift = reduce_arcs(old, ["dst", "more"], width, lambda dst, more: gauss_block(seed, dst, width) * (std * more.astype("f4"))[:, None])
    p1 = sum_vectors(factors.select("id", F.col("p1").alias("v")).unionByName(one), width).withColumnRenamed("v", "p1")
    p2 = sum_vectors(factors.select("id", F.col("p2").alias("v")).unionByName(two).unionByName(shift), width).withColumnRenamed("v", "p2")
    return after.nodes.join(p1, "id").join(p2, "id").select("id", "deg", "p1", "p2")


def touched(added: DataFrame) -> DataFrame:
    """The ends of new edges: (id)."""
    return graph.both_ways(added).select(F.col("src").alias("id")).distinct()


def affected(g: Graph, added: DataFrame, hops: int) -> tuple[DataFrame, DataFrame]:
    """Nodes (id, hop) within ``hops`` steps of the ends of new edges, and the arcs among them."""
    near = settle(graph.neighbourhood(g.arcs, touched(added), hops))
    inner = g.arcs.join(near.select(F.col("id").alias("src")), "src", "left_semi").join(near.select(F.col("id").alias("dst")), "dst", "left_semi")
    return near, inner


def refresh_embedding(state: State, after: Graph, added: DataFrame, mode: str = "ball") -> DataFrame:
    """(id, deg, v) of all nodes after ``added``.

    The forward pass runs on the nodes that the wanted vectors depend on; all others keep theirs.
    """
    depth = len(state.layers) - 1
    if mode not in ("ball", "touched"):
        raise ValueError("mode must be ball or touched")
    rewrite = 1 + depth if mode == "ball" else 0
    near = settle(graph.neighbourhood(after.arcs, touched(added), rewrite + depth + 1))
    # Arcs that lead from inside; at the rim sums are incomplete, which reaches no node that is rewritten.
    inside = after.arcs.join(near.select(F.col("id").alias("src")), "src", "left_semi")
    ring = inside.select(F.col("dst").alias("id")).unionByName(near.select("id")).distinct()
    part = Graph(after.nodes.join(ring, "id", "left_semi"), inside, after.n, after.m)
    y = settle(features.project(part, state.kind, state.layers[0], state.seed))
    z = gnn.forward(part, y, state.layers, state.seed, how="join")
    fresh = settle(z.join(near.where(F.col("hop") <= rewrite).select("id"), "id", "left_semi"))
    kept = state.embedding.join(fresh.select("id"), "id", "left_anti").select("id", "v").join(after.nodes, "id").select("id", "deg", "v")
    return settle(fresh.select("id", "deg", "v").unionByName(kept))


def update_tree(state: State, after: Graph, embedding: DataFrame) -> tuple[DataFrame, DataFrame, int]:
    """Blocks and tree after an update: nodes are routed by the stored planes; only sets whose verdict flips, and leaves on a
    path that has changed, are split anew.

    Gives blocks (id, block, path), the tree, and the number of nodes that changed their leaf. The tree has one row for
    each set, so it fits the driver.
    """
    tree = {r["path"]: r for r in state.tree.collect()}
    spark = embedding.sparkSession
    split = {p: (r["w"], r["b"]) for p, r in tree.items() if r["verdict"] == "split"}

    def route(batches):
        import pyarrow as pa

        from ..operators.kernels import matrix

        for b in batches:
            if b.num_rows:
                z = matrix(b.column(1), -1).astype("f8")
                path = np.full(len(z), "", object)
                work = [("", np.arange(len(z)))]
                while work:
                    at, own = work.pop()
                    path[own] = at
                    if at in split and len(own):
                        w, shift = split[at]
                        side = z[own] @ np.array(w) > shift
                        work += [(at + "0", own[~side]), (at + "1", own[side])]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(path.tolist(), pa.string())], ["id", "path"])

    placed = settle(embedding.where("deg > 0").select("id", "v").mapInArrow(route, "id long, path string"))
    moves = placed.join(state.blocks.select("id", F.col("path").alias("old")), "id", "left").where("old is null or old <> path").groupBy("path", "old").agg(F.count(F.lit(1)).alias("n")).collect()
    moved = sum(r["n"] for r in moves)
    changed = {r["path"] for r in moves} | {r["old"] for r in moves}
    stats = tree_stats(after, placed, spark)
    total = 2 * after.m
    flipped, kept = [], []
    for path in sorted(tree, key=len):
        if any(path.startswith(f) for f in flipped):
            continue
        now = stats.get(path)
        if path in split:
            one, two = stats.get(path + "0"), stats.get(path + "1")
            whole = now or {"n": 0, "m": 0}
            cut = whole["m"] - (one["m"] if one else 0) - (two["m"] if two else 0)
            keeps = one and two and selection.stays(one["n"], two["n"], one["vol"], two["vol"], cut, one["m"], two["m"], total, state.eps, "graph")
            if not keeps:
                flipped.append(path)
        elif now is not None:
            # A leaf on no changed path stays one: more edges elsewhere only make a split of it less likely.
            same = path not in changed and (now["n"], now["vol"], now["m"]) == (tree[path]["n"], tree[path]["vol"], tree[path]["m_in"])
            (kept if same else flipped).append(path)
    if any(stats[f]["n"] > selection.LOCAL_NODES for f in flipped if f in stats):
        return *selection.hierarchical(after, embedding.select("id", "v"), eps=state.eps, seed=state.seed), moved
    roots = F.broadcast(spark.createDataFrame([(f,) for f in flipped], "root string"))
    own = settle(embedding.join(placed, "id").join(roots, F.col("path").startswith(F.col("root"))).select("id", "deg", "v", F.col("root").alias("path")))
    one, two = (own.select(F.col("id").alias(e), F.col("path").alias(p)) for e, p in (("src", "p"), ("dst", "q")))
    edges = after.arcs.where("src < dst").select("src", "dst").join(one, "src").join(two, "dst").where("p = q").select("src", "dst", F.col("p").alias("path"))
    fresh = settle(selection.finish_sets(own, edges, total, state.eps, "graph", 64, {"seed": state.seed}))
    alone = after.nodes.where("deg = 0").select("id", F.lit("isolated").alias("path"))
    still = selection.of_sets(placed, kept) if kept else placed.limit(0)
    blocks = settle(selection.label(fresh.where("id is not null").select("id", "path").unionByName(still).unionByName(alone)))
    inner = [(p, r["parent"], stats[p]["n"], stats[p]["vol"], stats[p]["m"], stats[p]["m"] - stats[p + "0"]["m"] - stats[p + "1"]["m"], "split", list(r["w"]), r["b"]) for p, r in tree.items() if p in split and not any(p.startswith(f) for f in flipped)]
    inner += [tuple(tree[p][c] for c in ("path", "parent", "n", "vol", "m_in", "cut", "verdict", "w", "b")) for p in kept]
    return blocks, settle(spark.createDataFrame(inner, selection.TREE).unionByName(fresh.where("id is null").drop("id"))), moved


def prefix_counts(placed: DataFrame) -> DataFrame:
    """(path, n) for every set on the way from the root to each node's leaf; ``placed`` has (id, path)."""
    prefixes = F.explode(F.transform(F.sequence(F.lit(0), F.length("path")), lambda k: F.substring("path", F.lit(1), k)))
    return placed.select("id", prefixes.alias("path")).groupBy("path").agg(F.count(F.lit(1)).alias("n"))


def tree_stats(g: Graph, placed: DataFrame, spark) -> dict[str, dict]:
    """n, volume and inner edges of every set of the tree."""
    explode = lambda text: F.explode(F.transform(F.sequence(F.lit(0), F.length(text)), lambda k: F.substring(text, F.lit(1), k)))
    per_leaf = placed.join(g.nodes, "id").groupBy("path").agg(F.count(F.lit(1)).alias("n"), F.sum("deg").alias("vol"))
    sums = per_leaf.select("n", "vol", explode("path").alias("path")).groupBy("path").agg(F.sum("n").alias("n"), F.sum("vol").alias("vol"))
    one, two = (placed.select(F.col("id").alias(e), F.col("path").alias(p)) for e, p in (("src", "p"), ("dst", "q")))
    pairs = g.arcs.where("src < dst").select("src", "dst").join(one, "src").join(two, "dst").groupBy("p", "q").agg(F.count(F.lit(1)).alias("m"))
    shared = F.aggregate(F.sequence(F.lit(0), F.least(F.length("p"), F.length("q"))), F.lit(0), lambda best, k: F.when(F.substring("p", F.lit(1), k) == F.substring("q", F.lit(1), k), k).otherwise(best))
    inner = pairs.select("m", F.expr("p").substr(F.lit(1), shared).alias("common")).select("m", explode("common").alias("path")).groupBy("path").agg(F.sum("m").alias("m"))
    return {r["path"]: {"n": r["n"], "vol": r["vol"], "m": r["m"] or 0} for r in sums.join(inner, "path", "left").collect()}


def start(g: Graph, kind: str = "cut", layers: tuple[int, ...] = (32, 16), seed: int = 0, eps: int = 5) -> State:
    y = settle(features.project(g, kind, layers[0], seed))
    z = settle(gnn.forward(g, y, layers, seed))
    blocks, tree = selection.hierarchical(g, z, eps=eps, seed=seed)
    return State(g, z, blocks, tree, kind, layers, seed, eps)


def apply_batch(state: State, batch: DataFrame, mode: str = "ball") -> State:
    """The state after the edges (a, b) of one batch."""
    added = settle(new_edges(state.graph.arcs.where("src < dst"), batch))
    if added.isEmpty():
        return state
    after = grow(state.graph, added)
    z = refresh_embedding(state, after, added, mode)
    blocks, tree, _ = update_tree(state, after, z)
    return State(after, z, blocks, tree, state.kind, state.layers, state.seed, state.eps)


def refit(state: State) -> State:
    """A full selection on the current embedding."""
    blocks, tree = selection.hierarchical(state.graph, state.embedding, eps=state.eps, seed=state.seed)
    return State(state.graph, state.embedding, blocks, tree, state.kind, state.layers, state.seed, state.eps)


