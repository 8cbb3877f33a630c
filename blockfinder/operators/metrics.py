"""Measures of partitions and of graphs. What has ``_df`` in its name is a DataFrame; the rest are numbers."""

from __future__ import annotations

from collections import Counter

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .graph import Graph

MATCH_UP_TO = 2000  # blocks that are matched exactly on the driver


def contingency(truth: DataFrame, pred: DataFrame) -> DataFrame:
    """(r, s, n): nodes of true block r that are in found block s."""
    return truth.select("id", F.col("block").alias("r")).join(pred.select("id", F.col("block").alias("s")), "id").groupBy("r", "s").agg(F.count(F.lit(1)).alias("n"))


def pairs(n: Column) -> Column:
    """Pairs among n."""
    n = n.cast("decimal(19,0)")
    return (n * (n - 1) / 2).cast("decimal(38,0)")


def pair_counts_df(table: DataFrame) -> DataFrame:
    """One row: pairs together in both (both), in truth (truth), in the prediction (pred), and all (every)."""
    rows = table.groupBy("r").agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias("truth"))
    columns = table.groupBy("s").agg(F.sum("n").alias("n")).agg(F.sum(pairs(F.col("n"))).alias("pred"))
    cells = table.agg(F.sum(pairs(F.col("n"))).alias("both"), pairs(F.sum("n")).alias("every"))
    return cells.crossJoin(rows).crossJoin(columns)  # three single rows


def pairwise_df(table: DataFrame) -> DataFrame:
    """One row: precision, recall, f1, ari over pairs of nodes. Without any pair that counts, they are 1."""
    both, truth, pred, every = (F.col(c).cast("double") for c in ("both", "truth", "pred", "every"))
    expected = F.when(every > 0, truth * pred / every).otherwise(0.0)
    spread = (truth + pred) / 2 - expected

    def share(part: Column, of: Column) -> Column:
        return F.when(of > 0, part / of).otherwise(F.when(truth + pred == 0, 1.0).otherwise(0.0))

    return pair_counts_df(table).select(
        share(both, pred).alias("precision"), share(both, truth).alias("recall"), F.when(truth + pred > 0, 2 * both / (truth + pred)).otherwise(1.0).alias("f1"), F.when(spread != 0, (both - expected) / spread).otherwise(1.0).alias("ari")
    )


def matching(gain: np.ndarray) -> int:
    """The largest sum of a one-to-one choice of rows and columns, by shortest augmenting paths with potentials."""
    if gain.shape[0] > gain.shape[1]:
        gain = gain.T
    rows, columns = gain.shape
    cost = gain.max(initial=0) - gain.astype("f8")
    u, v, owner = np.zeros(rows), np.zeros(columns + 1), np.full(columns + 1, -1)
    for row in range(rows):
        owner[columns] = row
        at, least, back, used = columns, np.full(columns, np.inf), np.full(columns, columns), np.zeros(columns + 1, bool)
        while owner[at] != -1:
            used[at] = True
            free = ~used[:columns]
            step = cost[owner[at]] - u[owner[at]] - v[:columns]
            better = free & (step < least)
            least[better], back[better] = step[better], at
            to = int(np.where(free, least, np.inf).argmin())
            shift = least[to]
            u[owner[used]] += shift
            v[used] -= shift
            least[free] -= shift
            at = to
        while at != columns:
            owner[at] = owner[back[at]]
            at = back[at]
    taken = owner[:columns]
    return int(gain[taken[taken >= 0], np.flatnonzero(taken >= 0)].sum())


def accuracy(table: DataFrame) -> float:
    """The share of nodes in matched blocks, under the best one-to-one matching of blocks.

    Beyond ``MATCH_UP_TO`` blocks on either side, blocks are matched greedily by size, which is a lower bound.
    """
    return matched([(r["r"], r["s"], r["n"]) for r in table.collect()])


def matched(cells: list[tuple[int, int, int]]) -> float:
    if not cells:
        return 1.0
    rows, columns = sorted({c[0] for c in cells}), sorted({c[1] for c in cells})
    total = sum(c[2] for c in cells)
    if max(len(rows), len(columns)) <= MATCH_UP_TO:
        at, to = {r: k for k, r in enumerate(rows)}, {s: k for k, s in enumerate(columns)}
        gain = np.zeros((len(rows), len(columns)), "i8")
        for r, s, n in cells:
            gain[at[r], to[s]] = n
        return matching(gain) / total
    used_r, used_s, found = set(), set(), 0
    for r, s, n in sorted(cells, key=lambda c: (-c[2], c[0], c[1])):
        if r not in used_r and s not in used_s:
            used_r.add(r), used_s.add(s)
            found += n
    return found / total


def scores(truth: DataFrame, pred: DataFrame) -> dict[str, float]:
    """acc, ari, f1, recall, precision, k_true, k_found, k_error of nodes that both divide, from one pass over them.

    The driver sees the table of blocks against blocks, which ``accuracy`` needs as well; ``pairwise_df`` is the same as a plan.
    """
    cells = [(r["r"], r["s"], r["n"]) for r in contingency(truth, pred).collect()]
    rows, columns = Counter(), Counter()
    for r, s, n in cells:
        rows[r] += n
        columns[s] += n

    def together(counts) -> int:
        return sum(n * (n - 1) // 2 for n in counts)

    both, of_truth, of_pred, every = together(c[2] for c in cells), together(rows.values()), together(columns.values()), together([sum(rows.values())])
    none = 1.0 if of_truth + of_pred == 0 else 0.0
    expected = of_truth * of_pred / every if every else 0.0
    spread = (of_truth + of_pred) / 2 - expected
    return {
        "acc": matched(cells),
        "ari": (both - expected) / spread if spread else 1.0,
        "f1": 2 * both / (of_truth + of_pred) if of_truth + of_pred else 1.0,
        "recall": both / of_truth if of_truth else none,
        "precision": both / of_pred if of_pred else none,
        "k_true": len(rows),
        "k_found": len(columns),
        "k_error": len(columns) - len(rows),
    }


def block_pairs(g: Graph, blocks: DataFrame) -> DataFrame:
    """(r, s, arcs): arcs from block r to block s, both ways."""
    one, two = (blocks.select(F.col("id").alias(e), F.col("block").alias(c)) for e, c in (("src", "r"), ("dst", "s")))
    return g.arcs.select("src", "dst").join(one, "src").join(two, "dst").groupBy("r", "s").agg(F.count(F.lit(1)).alias("arcs"))


def block_sums(g: Graph, blocks: DataFrame) -> DataFrame:
    """(block, vol, own, cut): volume, arcs inside and arcs that leave."""
    table = block_pairs(g, blocks)
    return table.groupBy(F.col("r").alias("block")).agg(F.sum("arcs").alias("vol"), F.sum(F.when(F.col("r") == F.col("s"), F.col("arcs")).otherwise(0)).alias("own"), F.sum(F.when(F.col("r") != F.col("s"), F.col("arcs")).otherwise(0)).alias("cut"))


def ncut_df(g: Graph, blocks: DataFrame) -> DataFrame:
    """Half the sum over blocks of cut over volume; blocks without volume add nothing."""
    return block_sums(g, blocks).agg(F.coalesce(F.sum(F.col("cut") / F.col("vol")) / 2, F.lit(0.0)).alias("ncut"))


def ncut_trace_df(g: Graph, blocks: DataFrame) -> DataFrame:
    """tr(H' L H) with scaled indicators, edge by edge: twice the scalar form."""
    vol = block_sums(g, blocks).select("block", "vol")
    placed = blocks.select("id", "block").join(vol, "block")
    one, two = (placed.select(F.col("id").alias(e), F.col("block").alias(f"b_{e}"), F.col("vol").alias(f"v_{e}")) for e in ("src", "dst"))
    ends = g.arcs.where("src < dst").select("src", "dst").join(one, "src").join(two, "dst")
    # An edge inside a block has equal indicators over the root of the degree; one between blocks adds 1/vol of both.
    return ends.where("b_src <> b_dst").agg(F.coalesce(F.sum(1 / F.col("v_src") + 1 / F.col("v_dst")), F.lit(0.0)).alias("trace"))


def modularity_df(g: Graph, blocks: DataFrame) -> DataFrame:
    total = F.lit(float(max(1, 2 * g.m)))
    return block_sums(g, blocks).agg(F.coalesce(F.sum(F.col("own") / total - (F.col("vol") / total) * (F.col("vol") / total)), F.lit(0.0)).alias("modularity"))


def modularity_trace_df(g: Graph, blocks: DataFrame) -> DataFrame:
    """tr(H' Q H) = 2m times the modularity, from counts of arcs and products of volumes."""
    total = F.lit(float(max(1, 2 * g.m)))
    return block_sums(g, blocks).agg(F.coalesce(F.sum(F.col("own") - F.col("vol").cast("double") * F.col("vol") / total), F.lit(0.0)).alias("trace"))


def sbm_loglik_df(g: Graph, blocks: DataFrame) -> DataFrame:
    """The degree-corrected block model's profile log-likelihood, without terms that no partition changes."""
    table = block_pairs(g, blocks)
    vol = table.groupBy("r").agg(F.sum("arcs").alias("vol"))
    both = table.join(vol, "r").join(vol.select(F.col("r").alias("s"), F.col("vol").alias("vol_s")), "s")
    return both.agg(F.coalesce(F.sum(F.col("arcs") * F.log(F.col("arcs") / (F.col("vol").cast("double") * F.col("vol_s")))) / 2, F.lit(0.0)).alias("loglik"))


def number(df: DataFrame) -> float:
    return float(df.first()[0])


def distortion(z: DataFrame, reference: DataFrame, pairs: int = 2000, seed: int = 0) -> DataFrame:
    """How squared distances in ``z`` compare with those in ``reference`` (both id, v), over pairs drawn by a hash: quantiles of the ratio.

    Each of the ``pairs`` ids of the least hash is paired with the next one in hash order.
    """
    from pyspark.sql import Window

    from ..functions.rng import hash01

    both = z.select("id", F.col("v").alias("v1")).join(reference.select("id", F.col("v").alias("v2")), "id").withColumn("draw", hash01(seed, F.col("id"))).orderBy("draw", "id").limit(pairs)
    order = Window.partitionBy(F.lit(0)).orderBy("draw", "id")  # at most ``pairs`` rows
    both = both.withColumn("n1", F.lead("v1").over(order)).withColumn("n2", F.lead("v2").over(order)).where("n1 is not null")

    def far(a: str, b: str) -> Column:
        return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y).cast("double") * (x - y)), F.lit(0.0), lambda s, x: s + x)

    ratio = both.select((far("v1", "n1") / far("v2", "n2")).alias("ratio")).where("ratio is not null")
    return ratio.agg(F.count(F.lit(1)).alias("pairs"), F.round(F.percentile("ratio", 0.5), 6).alias("median"), F.round(F.percentile("ratio", 0.05), 6).alias("low"), F.round(F.percentile("ratio", 0.95), 6).alias("high"))
