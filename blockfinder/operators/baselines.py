"""Methods to compare with, written anew from the public literature on each family.

``greedy_modularity`` (rounds), ``sbm_parallel``, ``spectral_clustering``, ``label_propagation`` and ``trivial`` are
distributed. ``sbm_mcmc``, ``spectral_modularity``, ``belief_propagation`` and exact greedy merging are sequential by
nature: they run in one task and refuse graphs beyond ``ONE_TASK_EDGES`` edges. Of a sample for ``sbm_mcmc``, only the
edges within it go there, however many they are.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.rng import hash01, uniform_block
from ..plans.state import dropped, placed, settle, written
from . import bisect
from . import components as contraction
from .gnn import dealt_arcs, neighbour_sums, unit_rows
from .graph import Graph
from .kernels import matrix, reduce_arcs, vectors

ONE_TASK_EDGES = 2_000_000
FOLLOW_ROUNDS = 5
FEW = 32  # merges in a round from which on grown blocks have rows of their own
GROWN_BYTES = 256 << 20
MESSAGE_BYTES = 512 << 20  # of numbers of groups that are tried side by side
AT_ONCE = 11  # groups up to which numbers are tried side by side whatever is found
TRIAL_PARTS = 64
TURN = 1 << 16  # cells of messages that are renewed at a time


def named(df: DataFrame, block: str = "block") -> DataFrame:
    """(id, block) with each block called by its least id."""
    least = df.groupBy(block).agg(F.min("id").alias("least"))
    return df.join(least, block).select("id", F.col("least").alias("block"))


def in_one_task(g: Graph, method: Callable[[int, np.ndarray, np.ndarray], np.ndarray], most: int | None = ONE_TASK_EDGES) -> DataFrame:
    """(id, block) of ``method(n, a, b)``, which gets the places of the edges' ends and returns a label for each place."""
    if most is not None and g.m > most:
        raise ValueError(f"{g.m} edges; this method runs in one task and takes at most {most}")

    def run(left, right):
        ids = np.sort(left["id"].to_numpy())
        a, b = (np.searchsorted(ids, right[c].to_numpy()) if right.num_rows else np.zeros(0, "i8") for c in ("src", "dst"))
        order = np.lexsort((b, a))  # edges come in any order
        a, b = a[order], b[order]
        labels = method(len(ids), a, b) if len(ids) else np.zeros(0, "i8")
        return pa.table({"id": pa.array(ids, pa.int64()), "block": pa.array(np.asarray(labels, "i8"))})

    one = F.lit(0).alias("one")
    nodes, edges = g.nodes.select(one, "id").groupBy("one"), g.arcs.where("src < dst").select(one, "src", "dst").groupBy("one")
    # Written: what reads the blocks more than once would run the method again each time.
    return named(written(nodes.cogroup(edges).applyInArrow(run, "id long, block long")))


# Distributed methods.


def components(g: Graph) -> DataFrame:
    """Connected components; a block's name is its least node."""
    edges = g.arcs.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b"))
    found = contraction.components(edges).select(F.col("node").alias("id"), F.col("root").alias("block"))
    return g.nodes.select("id").join(found, "id", "left").select("id", F.coalesce("block", "id").alias("block"))


def label_propagation(g: Graph, rounds: int = 10, seed: int = 0) -> DataFrame:
    """Nodes take their neighbours' most frequent label (the least of equal ones), half of them in each round."""
    labels = settle(g.nodes.select("id", F.col("id").alias("block")))
    for k in range(rounds):
        seen = g.arcs.select("src", "dst").join(labels.select(F.col("id").alias("dst"), "block"), "dst").groupBy("src", "block").count()
        best = seen.groupBy(F.col("src").alias("id")).agg(F.max_by("block", F.struct("count", -F.col("block"))).alias("new"))
        coin = hash01(seed, F.col("id"), k) < 0.5
        labels = settle(labels.join(best, "id", "left").select("id", F.when(coin, F.coalesce("new", "block")).otherwise(F.col("block")).alias("block")))
    return named(labels)


def trivial(g: Graph, how: str, seed: int = 0) -> DataFrame:
    """``single``: one block. ``halves``: two by a coin. ``components`` and ``labels``: as their functions."""
    if how == "single":
        return named(g.nodes.select("id", F.lit(0).alias("block")))
    if how == "halves":
        return named(g.nodes.select("id", (hash01(seed, F.col("id")) < 0.5).cast("int").alias("block")))
    return {"components": components, "labels": label_propagation}[how](g)


def greedy_modularity(g: Graph, mode: str = "rounds", most_rounds: int | None = None) -> DataFrame:
    """Agglomeration while modularity grows. ``exact`` merges the best pair of all at each step, in one task; ``rounds``
    merges all pairs that are each other's best in each round.

    What a round leaves lies in tables, which are deleted after the next one: plans that start from them stay as short as the
    first, and the driver keeps nothing of old rounds.
    """
    if mode == "exact":
        return in_one_task(g, merge_best)
    spark, total = g.nodes.sparkSession, float(max(1, 2 * g.m))
    place = settle(g.nodes.select("id", F.col("id").alias("block")))
    arcs = settle(g.arcs.select(F.col("src").alias("r"), F.col("dst").alias("s"), F.lit(1).alias("e")))
    vol = settle(g.nodes.select(F.col("id").alias("r"), F.col("deg").alias("vol")))
    held: list[str] = []
    left, rounds = 2 * g.m, 0
    while left > 2 * ONE_TASK_EDGES and (most_rounds is None or rounds < most_rounds):  # both ways
        gains = arcs.where("r <> s").join(vol, "r").join(vol.select(F.col("r").alias("s"), F.col("vol").alias("vol_s")), "s")
        gain = 2 * (F.col("e") / total - F.col("vol") / total * (F.col("vol_s") / total))
        gains = gains.select("r", "s", gain.alias("gain")).where("gain > 0")
        # Equal gains are ordered alike from both sides, so that a best pair of all is always mutual.
        best, best_folder = placed(gains.groupBy("r").agg(F.max_by("s", F.struct("gain", F.xxhash64(F.least("r", "s"), F.greatest("r", "s")))).alias("s")))
        mutual, folder = placed(best.join(best.select(F.col("r").alias("s"), F.col("s").alias("back")), "s").where("back = r and r > s").select("r", F.col("s").alias("to")))
        now = [best_folder, folder]
        if mutual.isEmpty():
            dropped(spark, *now, *held)
            return named(place)
        place, folder = placed(place.join(mutual.withColumnRenamed("r", "block"), "block", "left").select("id", F.coalesce("to", "block").alias("block")))
        now.append(folder)
        moved = arcs.join(mutual, "r", "left").select(F.coalesce("to", "r").alias("r"), "s", "e").join(mutual.select(F.col("r").alias("s"), F.col("to").alias("t")), "s", "left")
        arcs, folder = placed(moved.groupBy("r", F.coalesce("t", "s").alias("s")).agg(F.sum("e").alias("e")))
        now.append(folder)
        vol, folder = placed(vol.join(mutual, "r", "left").groupBy(F.coalesce("to", "r").alias("r")).agg(F.sum("vol").alias("vol")))
        now.append(folder)
        dropped(spark, *held)
        held, left, rounds = now, arcs.count(), rounds + 1
    if most_rounds is None or rounds < most_rounds:
        place = place.join(written(finish_rounds(arcs, vol, total)).withColumnRenamed("r", "block"), "block").select("id", F.col("to").alias("block"))
    place = written(place)
    dropped(spark, *held)
    return named(place)


def finish_rounds(arcs: DataFrame, vol: DataFrame, total: float) -> DataFrame:
    """(r, to): the same rounds for a contracted graph that one task can hold."""

    def run(left, right):
        names = np.sort(left["r"].to_numpy())
        volume = left["vol"].to_numpy()[np.argsort(left["r"].to_numpy())].astype("f8")
        to = np.arange(len(names))
        if right.num_rows:
            r, s = (np.searchsorted(names, right[c].to_numpy()) for c in ("r", "s"))
            to = rounds_in_memory(len(names), r, s, right["e"].to_numpy().astype("f8"), volume, total)
        return pa.table({"r": pa.array(names, pa.int64()), "to": pa.array(names[to], pa.int64())})

    one = F.lit(0).alias("one")
    return vol.select(one, "r", "vol").groupBy("one").cogroup(arcs.select(one, "r", "s", "e").groupBy("one")).applyInArrow(run, "r long, to long")


def rounds_in_memory(n: int, r: np.ndarray, s: np.ndarray, e: np.ndarray, vol: np.ndarray, total: float, target: int = 1) -> np.ndarray:
    """Mutual best merges, round by round, until none gains or ``target`` blocks are left. Gives each block's final one.

    Cells of pairs of blocks stay sorted and summed from round to round; a round touches those of merged blocks. Where
    few pairs are left in a round, as when large blocks take one small one each, ``rounds_of_few`` goes on.
    """
    labels = np.arange(n)
    alive = n
    apart = r != s
    cell, where = np.unique(r[apart] * n + s[apart], return_inverse=True)
    weight = np.bincount(where, e[apart], len(cell))
    while alive > target and len(cell):
        x, y = np.divmod(cell, n)
        gain = weight / total - vol[x] * vol[y] / total**2
        starts = np.flatnonzero(np.r_[True, x[1:] != x[:-1]])
        top = np.repeat(np.maximum.reduceat(gain, starts), np.diff(np.r_[starts, len(x)]))
        good = np.flatnonzero((gain > 0) & (gain == top))
        u, v = x[good], y[good]
        order = np.argsort(np.minimum(u, v) * 31 + np.maximum(u, v), kind="stable")
        best = np.full(n, -1)
        best[u[order]] = v[order]
        mutual = np.flatnonzero((best >= 0) & (best[np.maximum(best, 0)] == np.arange(n)) & (best < np.arange(n)))
        if not len(mutual):
            break
        to = np.arange(n)
        to[mutual] = best[mutual]
        vol = np.bincount(to, vol, n)
        labels = to[labels]
        alive -= len(mutual)
        gone = np.zeros(n, bool)
        gone[mutual] = True
        moved = gone[x] | gone[y]
        p, q = to[x[moved]], to[y[moved]]
        new, where = np.unique((p * n + q)[p != q], return_inverse=True)
        more = np.bincount(where, weight[moved][p != q], len(new))
        cell, weight = cell[~moved], weight[~moved]
        at = np.searchsorted(cell, new)
        there = at < len(cell)
        there[there] = cell[at[there]] == new[there]
        weight[at[there]] += more[there]
        cell, weight = np.insert(cell, at[~there], new[~there]), np.insert(weight, at[~there], more[~there])
        if alive > target and len(cell) and len(mutual) < max(FEW, alive // 512):
            left = np.unique(labels)
            x, y = (np.searchsorted(left, part) for part in np.divmod(cell, n))
            to, again = rounds_of_few(left, x, y, weight, vol[left], total, target)
            labels = left[to][np.searchsorted(left, labels)]
            if again is None:
                break
            vol = np.bincount(left[to], vol[left], n)
            alive = int((to == np.arange(len(left))).sum())
            cell, weight = left[again[0]] * n + left[again[1]], again[2]
    return labels


def rounds_of_few(names: np.ndarray, x: np.ndarray, y: np.ndarray, weight: np.ndarray, vol: np.ndarray, total: float, target: int) -> tuple[np.ndarray, tuple[np.ndarray, np.ndarray, np.ndarray] | None]:
    """The same rounds where few pairs merge in each. Gives each block's final one and, if rounds are left, the cells.

    Blocks that have merged ("grown") have a dense row of weights. Gains between two others stay as they are, so their
    neighbours are sorted once; only rows of grown blocks are asked again. Other gains of a grown block fall as it grows
    until a weight rises, so that its best few and those that rose are asked while they beat what the rest had. Stops early once half of the blocks are gone or
    the rows take too much.
    """
    n, square, vol = len(names), total**2, vol.copy()
    start = np.searchsorted(x, np.arange(n + 1))
    gain = weight / total - vol[x] * vol[y] / square
    good = np.flatnonzero(gain > 0)
    key = np.minimum(names[x[good]], names[y[good]]) * 31 + np.maximum(names[x[good]], names[y[good]])
    good = good[np.lexsort((-y[good], -key, -gain[good], x[good]))]
    liked, liked_gain = np.r_[y[good], -1], np.r_[gain[good], -1.0]
    bounds = np.searchsorted(x[good], np.arange(n + 1))
    at, end = bounds[:-1].copy(), bounds[1:]
    plain = np.ones(n, bool)  # neither grown nor gone
    blocked = np.full(n, -1)  # a grown block that was better than the best plain neighbour
    to, alive = np.arange(n), n
    most = max(1, GROWN_BYTES // (4 * n))
    rows = np.zeros((min(64, most + FEW), n), "i4" if total < 2**31 else "i8")
    column: list[int] = []  # of each row
    row_of = np.full(n, -1)
    best: list[tuple[float, int]] = []  # each row's gain and partner
    few: list[np.ndarray | None] = []  # each row's likely partners
    floor: list[float] = []  # no other one, but grown ones, is better
    wide = max(64, n // 256)

    def order(i: int, j: int) -> tuple[int, int]:
        a, b = int(names[i]), int(names[j])
        return min(a, b) * 31 + max(a, b), b

    def ask_row(h: int) -> tuple[float, int]:
        i, whole = column[h], few[h] is None or len(few[h]) > 8 * wide
        while True:
            some = slice(None) if whole else np.concatenate([few[h], np.array(column)])
            own = vol[some] * vol[i]
            own /= square
            gains = rows[h, some] / total
            gains -= own
            top = gains.max()
            if whole or top > floor[h]:
                break
            whole = True
        if whole:
            few[h], floor[h] = np.arange(n), 0.0
            if n > 2 * wide:
                sides = np.argpartition(gains, n - wide)
                few[h], floor[h] = sides[n - wide :], max(0.0, float(gains[sides[: n - wide]].max()))
        if top <= 0:
            return -1.0, -1
        same = np.flatnonzero(gains == top)
        same = same if whole else some[same]
        return float(top), int(same[0]) if len(same) == 1 else max((int(j) for j in same), key=lambda j: order(i, j))

    def with_rows(blocks: np.ndarray | int) -> np.ndarray:
        """Gains of all grown blocks with these."""
        h = len(column)
        own = vol[column] if np.ndim(blocks) == 0 else vol[column][:, None]
        return rows[:h, blocks] / total - own * vol[blocks] / square

    def partner(i: int) -> int:
        """The best of a plain block."""
        near = float(liked_gain[at[i]]) if at[i] < end[i] else -1.0
        gains = with_rows(i)
        top = float(gains.max(initial=-1.0))
        if near > top or top <= 0:
            return int(liked[at[i]]) if near > 0 else -1
        same = [column[h] for h in np.flatnonzero(gains == top)] + ([int(liked[at[i]])] if near == top else [])
        return max(same, key=lambda j: order(i, j))

    def row(i: int) -> np.ndarray:
        if row_of[i] >= 0:
            return rows[row_of[i]]
        out = np.zeros(n, rows.dtype)
        near, e = y[start[i] : start[i + 1]], weight[start[i] : start[i + 1]]
        out[near] = e * plain[near]
        out[column] = rows[: len(column), i]
        return out

    def merge(i: int, j: int) -> None:
        nonlocal rows
        h, g, other = len(column), int(row_of[i]), int(row_of[j])
        if (g < 0) != (other < 0):
            g, one = (g, j) if g >= 0 else (other, i)
            near, e = y[start[one] : start[one + 1]], weight[start[one] : start[one + 1]]
            near, e = near[plain[near]], e[plain[near]]
            joined = None
            rows[g, near] += e.astype(rows.dtype)
            rows[g, column] += rows[:h, one]
            if few[g] is not None:
                few[g] = np.concatenate([few[g], near])
        else:
            joined = row(i) + row(j)
        rows[:h, i] += rows[:h, j]
        rows[:h, j] = 0
        if joined is not None and g >= 0:
            for kept in (rows, column, best, few, floor):
                kept[other] = kept[h - 1]
            row_of[column[other]] = other
            for kept in (column, best, few, floor):
                kept.pop()
            g = int(row_of[i])
        elif joined is not None:
            g = h
            if g == len(rows):
                rows = np.concatenate([rows, np.zeros_like(rows)])
            column.append(i)
            best.append((-1.0, -1))
            few.append(None)
            floor.append(0.0)
        if joined is not None:
            rows[g], few[g] = joined, None
        column[g] = i
        rows[g, [i, j]] = 0
        row_of[j], row_of[i] = -1, g
        plain[i] = plain[j] = False
        vol[i] += vol[j]
        vol[j] = 0
        to[j] = i

    def like_next(z: np.ndarray) -> np.ndarray:
        """These plain blocks' best plain neighbours; gives the second block of each new pair that like each other."""
        stale = z[at[z] < end[z]]
        while len(stale := stale[~plain[liked[at[stale]]]]):
            at[stale] += 1
            stale = stale[at[stale] < end[stale]]
        like[z] = np.where(at[z] < end[z], liked[np.minimum(at[z], len(liked) - 1)], -1)
        z = z[like[z] >= 0]
        z = z[like[like[z]] == z]
        return np.unique(np.maximum(z, like[z]))

    like = np.full(n, -1)
    both = like_next(np.arange(n))
    ended = False
    while alive > target and len(column) < most and (alive >= n // 2 or n <= 4096):
        u = both
        v = like[u]
        if column:
            columns, held = np.array(column), np.zeros(len(u), bool)
            for z in (u, v):
                h = row_of[np.maximum(blocked[z], 0)]
                held |= (blocked[z] >= 0) & (h >= 0) & (rows[h, z] / total - vol[columns[h]] * vol[z] / square > liked_gain[at[z]])
            u, v = u[~held], v[~held]
            asked = np.unique(np.r_[u, v])
            gains = with_rows(asked)
            top, own = gains.max(axis=0), np.ones(n, bool)
            better = top > liked_gain[at[asked]]
            blocked[asked[better]] = columns[gains.argmax(axis=0)[better]]
            own[asked[better]] = False
            for z in asked[top == liked_gain[at[asked]]].tolist():
                own[z] = partner(z) == like[z]
            u, v = u[own[u] & own[v]], v[own[u] & own[v]]
        merged = list(zip(v.tolist(), u.tolist(), strict=True))
        for i, (_, j) in zip(column, best, strict=True):
            if j >= 0 and row_of[j] < 0 and partner(j) == i or j > i and row_of[j] >= 0 and best[row_of[j]][1] == i:
                merged.append((min(i, j), max(i, j)))
        ended = not merged
        if ended:
            break
        were_plain = [t for pair in merged for t in pair if plain[t]]
        for i, j in merged:
            merge(i, j)
        alive -= len(merged)
        if were_plain:
            like[were_plain] = -1
            near = np.concatenate([y[start[t] : start[t + 1]] for t in were_plain])
            near = np.unique(near[plain[near]])
            both = both[plain[both] & plain[like[both]]]
            both = np.union1d(both, like_next(near[(like[near] >= 0) & ~plain[like[near]]]))
        touched, kept = {i for pair in merged for i in pair}, np.array([i for i, _ in merged])
        gains = with_rows(kept)
        for h in range(len(column)):
            if column[h] in touched or best[h][1] in touched:
                best[h] = ask_row(h)
                continue
            for k in np.flatnonzero((gains[h] > 0) & (gains[h] >= best[h][0])):
                g, j = float(gains[h, k]), int(kept[k])
                if (g, order(column[h], j)) > (best[h][0], order(column[h], best[h][1])):
                    best[h] = g, j
    while (to != to[to]).any():
        to = to[to]
    if ended or alive <= target:
        return to, None
    h, z = np.nonzero(rows[: len(column)])
    grown, e = np.array(column)[h], rows[h, z].astype("f8")
    old, one = plain[x] & plain[y], plain[z]
    p, q = np.r_[x[old], grown, z[one]], np.r_[y[old], z, grown[one]]
    sorted_ = np.lexsort((q, p))
    return to, (p[sorted_], q[sorted_], np.r_[weight[old], e, e[one]][sorted_])


def sbm_parallel(g: Graph, seed: int = 0, rounds: int = 12, start_blocks: int | None = None) -> DataFrame:
    """Block-model inference where all nodes may move at once against frozen counts, then merges of whole blocks.

    Starts from rounds of mutual best merges. Blocks are counted in a small table on the driver; nodes never are.
    """
    start = named(greedy_modularity(g))
    names = {r["block"]: k for k, r in enumerate(start.select("block").distinct().orderBy("block").collect())}
    if len(names) > (start_blocks or 4096):
        raise ValueError("more start blocks than the driver's table may have")
    code = g.nodes.sparkSession.createDataFrame(list(names.items()), "block long, b int")
    labels = settle(start.join(F.broadcast(code), "block").select("id", "b"))
    width = len(names)

    def counts() -> np.ndarray:
        one, two = labels.select(F.col("id").alias("src"), F.col("b").alias("r")), labels.select(F.col("id").alias("dst"), F.col("b").alias("s"))
        out = np.zeros((width, width))
        for row in g.arcs.select("src", "dst").join(one, "src").join(two, "dst").groupBy("r", "s").count().collect():
            out[row["r"], row["s"]] = row["count"]
        return out

    for k in range(rounds):
        table = counts()
        near = g.arcs.select("src", "dst").join(labels.select(F.col("id").alias("dst"), "b"), "dst")
        seen = reduce_arcs(near, ["b"], width, lambda b: np.eye(width, dtype="f4")[b])
        odds = affinity(table)

        def move(batches, odds=odds, k=k):
            for x in batches:
                if x.num_rows:
                    ids, old = x.column(0).to_numpy(), x.column(1).to_numpy()
                    new = (matrix(x.column(2), width).astype("f8") @ odds.T).argmax(axis=1)
                    coin = uniform_block(seed * 977 + k, ids, 1)[:, 0] < 0.5
                    yield pa.RecordBatch.from_arrays([x.column(0), pa.array(np.where(coin, new, old).astype("i4"))], ["id", "b"])

        moved = labels.join(seen, "id").select("id", "b", "v").mapInArrow(move, "id long, b int")
        labels = settle(moved.unionByName(labels.join(seen, "id", "left_anti")))
    to = merge_blocks(counts(), g.n)
    return named(labels.join(F.broadcast(g.nodes.sparkSession.createDataFrame(list(enumerate(to.tolist())), "b int, block int")), "b").select("id", "block"))


def spectral_clustering(g: Graph, k: int, seed: int = 0, iterations: int = 15) -> DataFrame:
    """For a given number of blocks: leading vectors of the normalised adjacency by block orthogonal iteration, then K-means."""
    from .features import with_all_nodes
    from ..functions.rng import gauss_block

    def first(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), vectors(gauss_block(seed, b.column(0).to_numpy(), k))], ["id", "v"])

    def times(w: np.ndarray | None, power: float):
        def run(batches):
            for b in batches:
                if b.num_rows:
                    rows = matrix(b.column(2), k).astype("f8")
                    rows = (rows if w is None else rows @ w) * np.maximum(b.column(1).to_numpy(), 1.0)[:, None] ** power
                    yield pa.RecordBatch.from_arrays([b.column(0), vectors(rows)], ["id", "v"])

        return run

    def gram(batches):
        total = np.zeros((k, k))
        for b in batches:
            if b.num_rows:
                rows = matrix(b.column(1), k).astype("f8")
                total += rows.T @ rows
        yield pa.RecordBatch.from_arrays([pa.array(range(k * k), pa.int64()), pa.array(total.reshape(-1))], ["cell", "x"])

    q = g.nodes.select("id").mapInArrow(first, "id long, v array<float>")
    arcs = dealt_arcs(g, loops=False)
    w = None
    for _ in range(iterations):
        scaled = settle(g.nodes.join(q, "id").select("id", "deg", "v").mapInArrow(times(w, -0.5), "id long, v array<float>"))
        sums = with_all_nodes(g, neighbour_sums(g, scaled, k, arcs=arcs), k)
        # Half of the identity is added, so that the largest eigenvalues are the ones that stand out.
        half = g.nodes.join(sums, "id").select("id", "deg", "v").mapInArrow(times(None, -0.5), "id long, v array<float>")
        back = g.nodes.join(scaled, "id").select("id", "deg", "v").mapInArrow(times(None, 0.5), "id long, v array<float>").withColumnRenamed("v", "u")
        q = settle(half.join(back, "id").select("id", F.zip_with("v", "u", lambda x, y: x + y * 0.5).cast("array<float>").alias("v")))
        cells = q.select("id", "v").mapInArrow(gram, "cell long, x double").groupBy("cell").agg(F.sum("x").alias("x")).collect()
        whole = np.zeros(k * k)
        for r in cells:
            whole[r["cell"]] = r["x"]
        values, turn = np.linalg.eigh(whole.reshape(k, k))
        w = turn / np.sqrt(np.maximum(values, 1e-12))

    def last(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), vectors(unit_rows(matrix(b.column(1), k).astype("f8") @ w))], ["id", "v"])

    # Written: K-means reads the rows again and again, and Spark's merge joins fail under one Python step upon another.
    return bisect.k_means(written(q.mapInArrow(last, "id long, v array<float>")), k, seed)


# Small tables of blocks.


def affinity(table: np.ndarray) -> np.ndarray:
    """The log-likelihood that one more edge to block t adds to a member of block s, for each (s, t)."""
    vol = table.sum(axis=1)
    return np.log((table + 0.5) / np.maximum(np.outer(vol, vol), 1.0)) + np.where(vol > 0, 0.0, -1e3)[:, None]


def xlogx(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.maximum(x, 1e-12))


def description_length(table: np.ndarray, n: int) -> float:
    """Of a degree-corrected block model with the counts ``table`` (arcs both ways) over n nodes."""
    vol, edges = table.sum(axis=1), table.sum() / 2
    used = int((vol > 0).sum())
    if not edges:
        return 0.0
    x = used * used / edges
    fit = (xlogx(table).sum() - 2 * xlogx(vol).sum()) / 2
    return edges * ((1 + x) * np.log(1 + x) - (x * np.log(x) if x else 0)) + n * np.log(max(1, used)) - fit


def merge_costs(table: np.ndarray) -> np.ndarray:
    """What the fit loses by each merge of two blocks."""
    vol, f = table.sum(axis=1), xlogx(table)
    k = len(table)
    out = np.full((k, k), np.inf)
    rows = f.sum(axis=1)
    for r in range(k):
        joined = table[r] + table
        new = xlogx(joined)
        own = table[r, r] + 2 * table[r] + np.diagonal(table)
        # Rows r and s become one, whose own cells fold together.
        part = new.sum(axis=1) - new[:, r] - new[np.arange(k), np.arange(k)]
        old = rows[r] + rows - f[r, r] - f[r] - f[:, r] - np.diagonal(f)
        inner = xlogx(own) - f[r, r] - 2 * f[r] - np.diagonal(f)
        volume = xlogx(vol[r] + vol) - xlogx(vol[r]) - xlogx(vol)
        out[r] = -(2 * (part - old) + inner - 2 * volume) / 2
        out[r, r] = np.inf
    return out


def merge_blocks(table: np.ndarray, n: int, down_to: int = 1) -> np.ndarray:
    """Merge the cheapest pair while the description gets shorter; each block's final label."""
    labels, table = np.arange(len(table)), table.copy()
    alive = list(np.flatnonzero(table.sum(axis=1) > 0))
    length = description_length(table, n)
    while len(alive) > down_to:
        part = table[np.ix_(alive, alive)]
        i, j = divmod(int(merge_costs(part).argmin()), len(alive))
        r, s = alive[min(i, j)], alive[max(i, j)]
        new = table.copy()
        new[r] += new[s]
        new[:, r] += new[:, s]
        new[s] = 0
        new[:, s] = 0
        shorter = description_length(new, n)
        if shorter >= length:
            break
        table, length = new, shorter
        labels[labels == s] = r
        alive.remove(s)
    return labels


# Methods in one task.


def merge_best(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The best merge of all at each step; of equal gains, the pair with the least names.

    A heap has each row's best pair. Between two merges of a block its gains only fall, and those that a merge lifts are in
    the merged block's own row, so that old entries are upper bounds: one that comes up is asked again.
    """
    total = 2.0 * max(1, len(a))
    cell, weight = np.unique(np.r_[a * n + b, b * n + a], return_counts=True)
    src, dst = np.divmod(cell, n)
    bounds = np.searchsorted(src, np.arange(n + 1))
    rows = [(dst[x:y], weight[x:y].astype("f8")) for x, y in zip(bounds[:-1], bounds[1:], strict=True)]
    vol = np.bincount(src, weight, n)
    top = np.arange(n)  # each node's block
    members = [np.array([i]) for i in range(n)]
    version = [0] * n

    def current(i: int) -> tuple[np.ndarray, np.ndarray]:
        """The row with neighbours by their present names."""
        ids, e = rows[i]
        now = top[ids]
        old = np.flatnonzero(now != ids)
        if len(old):
            kept = np.ones(len(ids), bool)
            kept[old] = False
            other = old[now[old] != i]
            rows[i] = added(ids[kept], e[kept], now[other], e[other])
        return rows[i]

    def push(i: int) -> None:
        ids, e = current(i)
        if len(ids):
            gain = e / total - vol[i] * vol[ids] / total**2
            k = int(gain.argmax())
            if gain[k] > 0:
                j = int(ids[k])
                heapq.heappush(heap, (-float(gain[k]), min(i, j), max(i, j), version[min(i, j)], version[max(i, j)], i))

    heap: list[tuple] = []
    for i in range(n):
        push(i)
    while heap:
        _, i, j, vi, vj, row = heapq.heappop(heap)
        if top[row] != row:
            continue
        if top[i] != i or top[j] != j or version[i] != vi or version[j] != vj:
            push(row)
            continue
        more = current(j)
        top[members[j]] = i
        members[i] = np.concatenate([members[i], members[j]])
        ids, e = current(i)
        rows[i] = added(ids, e, more[0][more[0] != i], more[1][more[0] != i])
        rows[j], members[j] = more[:0], members[j][:0]
        vol[i] += vol[j]
        version[i] += 1
        push(i)
    return top


def added(ids: np.ndarray, e: np.ndarray, more: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two rows as one, by id; ``ids`` rise and are each there once."""
    if not len(more):
        return ids, e
    new, where = np.unique(more, return_inverse=True)
    lift = np.bincount(where, weights, len(new))
    at = np.searchsorted(ids, new)
    there = at < len(ids)
    there[there] = ids[at[there]] == new[there]
    e = e.copy()
    e[at[there]] += lift[there]
    return np.insert(ids, at[~there], new[~there]), np.insert(e, at[~there], lift[~there])


def csr(n: int, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    src, dst = np.r_[a, b], np.r_[b, a]
    order = np.argsort(src, kind="stable")
    return np.searchsorted(src[order], np.arange(n + 1)), dst[order]


def block_table(labels: np.ndarray, k: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    table = np.bincount(labels[a] * k + labels[b], minlength=k * k).reshape(k, k).astype("f8")
    return table + table.T


def sbm_mcmc(g: Graph, seed: int = 0, beta: float = 3.0, max_sweeps: int = 12, strategy: str = "agglomerative", sample_fraction: float = 1.0) -> DataFrame:
    """Bayesian inference of the degree-corrected block model by a Markov chain.

    Blocks are merged step by step; after each step nodes move by Metropolis steps; the number of blocks with the
    shortest description stays. ``top_down`` divides the graph first and infers within the parts. With
    ``sample_fraction`` under 1, a sample of nodes is inferred and the others follow their neighbours.
    """

    def run(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        rng = np.random.default_rng(seed)
        if strategy == "top_down":
            halves = spectral_labels(n, a, b, depth=2)
            out = np.zeros(n, "i8")
            for k in np.unique(halves):
                own = np.flatnonzero(halves == k)
                place = np.full(n, -1)
                place[own] = np.arange(len(own))
                inner = (place[a] >= 0) & (place[b] >= 0)
                out[own] = infer(len(own), place[a][inner], place[b][inner], rng, beta, max_sweeps) + n * int(k)
            return out
        if sample_fraction < 1:
            keep = uniform_block(seed, np.arange(n), 1)[:, 0] < sample_fraction
            place = np.cumsum(keep) - 1
            inner = keep[a] & keep[b]
            labels, own = np.full(n, -1), np.flatnonzero(keep)
            _, first, code = np.unique(infer(len(own), place[a][inner], place[b][inner], rng, beta, max_sweeps), return_index=True, return_inverse=True)
            labels[own] = own[first[code]]
            return follow(labels, n, a, b)
        return infer(n, a, b, rng, beta, max_sweeps)

    if sample_fraction < 1 and strategy != "top_down" and g.m > ONE_TASK_EDGES:
        sample = settle(sampled(g, seed, sample_fraction))
        inner = g.arcs.join(sample.select(F.col("id").alias("src")), "src", "left_semi").join(sample.select(F.col("id").alias("dst")), "dst", "left_semi")
        part = Graph(sample, written(inner.where("src < dst").select("src", "dst")), 0, 0)
        return followed(g, in_one_task(part, lambda n, a, b: infer(n, a, b, np.random.default_rng(seed), beta, max_sweeps), None))
    return in_one_task(g, run)


def sampled(g: Graph, seed: int, fraction: float) -> DataFrame:
    """(id) of the nodes whose place in order is drawn."""
    rows = written(g.nodes.select("id").orderBy("id").withColumn("row", F.monotonically_increasing_id()))  # numbered from each part's 2^33 on
    sizes = {r["part"]: r["count"] for r in rows.groupBy(F.shiftright("row", 33).alias("part")).count().collect()}
    before = dict(zip(sorted(sizes), np.cumsum([0, *[sizes[k] for k in sorted(sizes)]]).tolist(), strict=False))

    def drawn(batches):
        for batch in batches:
            row = batch.column(1).to_numpy()
            place = row % (1 << 33) + np.array([before[k] for k in (row >> 33).tolist()], "i8")
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(uniform_block(seed, place, 1)[:, 0] < fraction))], ["id"])

    return rows.mapInArrow(drawn, "id long")


def followed(g: Graph, labels: DataFrame) -> DataFrame:
    """As ``follow``, for nodes that are not in ``labels`` (id, block), distributed."""
    labels = written(labels)
    for _ in range(FOLLOW_ROUNDS):
        rest = g.nodes.select("id").join(labels, "id", "left_anti")
        near = g.arcs.select("src", "dst").join(rest.select(F.col("id").alias("src")), "src", "left_semi")
        seen = near.join(labels.select(F.col("id").alias("dst"), "block"), "dst").groupBy("src", "block").count()
        new = written(seen.groupBy(F.col("src").alias("id")).agg(F.max_by("block", F.struct("count", -F.col("block"))).alias("block")))
        if new.isEmpty():
            break
        labels = written(labels.unionByName(new))
    return named(g.nodes.select("id").join(labels, "id", "left").select("id", F.coalesce("block", "id").alias("block")))


def follow(labels: np.ndarray, n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Nodes without a label (-1) take their neighbours' most frequent one (the least of equal ones), round by round; what
    is left is its own. A label is the place of one of its nodes."""
    src, dst = np.r_[a, b], np.r_[b, a]
    for _ in range(FOLLOW_ROUNDS):
        near = (labels[src] < 0) & (labels[dst] >= 0)
        if not near.any():
            break
        cell, count = np.unique(src[near] * n + labels[dst[near]], return_counts=True)
        node, block = np.divmod(cell, n)
        order = np.lexsort((-block, count, node))
        last = order[np.r_[np.diff(node[order]) > 0, True]]
        labels[node[last]] = block[last]
    return np.where(labels < 0, np.arange(n), labels)


def infer(n: int, a: np.ndarray, b: np.ndarray, rng: np.random.Generator, beta: float, max_sweeps: int) -> np.ndarray:
    if not len(a):
        return np.arange(n)
    labels = np.unique(merge_rounds(n, a, b, max(8, int(2 * n**0.5))), return_inverse=True)[1]
    start, near = csr(n, a, b)
    best, least = labels, np.inf
    k = int(labels.max()) + 1
    while True:
        labels = chain(labels, k, start, near, a, b, rng, beta, max_sweeps)
        labels = np.unique(labels, return_inverse=True)[1]
        k = int(labels.max()) + 1
        table = block_table(labels, k, a, b)
        length = description_length(table, n)
        if length < least:
            best, least = labels, length
        elif length > least * 1.02 and k < (best.max() + 1) * 0.6 or k == 1:
            break
        if k == 1:
            break
        # The step is small near where the shortest description is looked for.
        target = max(1, int(k * 0.75) if k > 30 else k - max(1, k // 10))
        labels = merge_to(labels, table, target)
        k = int(labels.max()) + 1
    return best


def merge_rounds(n: int, a: np.ndarray, b: np.ndarray, target: int) -> np.ndarray:
    """Start blocks: mutual best merges by modularity until at most ``target`` are left or none gains."""
    r, s = np.r_[a, b], np.r_[b, a]
    return rounds_in_memory(n, r, s, np.ones(len(r)), np.bincount(r, minlength=n).astype("f8"), 2.0 * len(a), target)


def merge_to(labels: np.ndarray, table: np.ndarray, target: int) -> np.ndarray:
    """Merge cheapest pairs, several in each step where many are to go, down to ``target`` blocks."""
    k = len(table)
    to = np.arange(k)
    left = k - target
    while left > 0:
        alive = np.flatnonzero(to == np.arange(k))
        cost = merge_costs(table[np.ix_(alive, alive)])
        partner = cost.argmin(axis=1)
        done: set[int] = set()
        for i in np.argsort(cost.min(axis=1)):
            j = partner[i]
            if left and i not in done and j not in done:
                done |= {i, j}
                r, s = alive[min(i, j)], alive[max(i, j)]
                to[to == s] = r
                table[r] += table[s]
                table[:, r] += table[:, s]
                table[s], table[:, s] = 0, 0
                left -= 1
                if len(done) > max(2, len(alive) // 4):
                    break
    return np.unique(to[labels], return_inverse=True)[1]


def chain(labels: np.ndarray, k: int, start: np.ndarray, near: np.ndarray, a: np.ndarray, b: np.ndarray, rng: np.random.Generator, beta: float, sweeps: int) -> np.ndarray:
    """Metropolis sweeps: batches of nodes propose blocks near their neighbours' blocks and move by the change of fit."""
    n = len(labels)
    deg = np.diff(start)
    last = np.inf
    for _ in range(sweeps):
        for batch in np.array_split(rng.permutation(n), 4):
            table = block_table(labels, k, a, b)
            odds = affinity(table)
            own = batch[deg[batch] > 0]
            pick = near[start[own] + (rng.random(len(own)) * deg[own]).astype("i8")]
            walk = np.cumsum(table + 1.0, axis=1)
            walk = walk / walk[:, -1:] + np.arange(k)[:, None]
            via = labels[pick]
            to = (np.searchsorted(walk.reshape(-1), via + rng.random(len(own))) - via * k).clip(max=k - 1)
            # The change of fit is summed over a node's own arcs: no table of nodes and blocks.
            firsts = np.r_[0, np.cumsum(deg[own])[:-1]]
            arc = np.arange(int(deg[own].sum())) + np.repeat(start[own] - firsts, deg[own])
            there = labels[near[arc]]
            change = odds[np.repeat(to, deg[own]), there] - odds[np.repeat(labels[own], deg[own]), there]
            gain = np.add.reduceat(change, firsts) if len(own) else change
            move = np.log(rng.random(len(own))) < beta * gain
            labels = labels.copy()
            labels[own[move]] = to[move]
        now = description_length(block_table(labels, k, a, b), n)
        if last - now < 1e-4 * abs(now):
            break
        last = now
    return labels


def spectral_labels(n: int, a: np.ndarray, b: np.ndarray, depth: int = 64, iterations: int = 300, least: int = 1) -> np.ndarray:
    deg = np.bincount(np.r_[a, b], minlength=n).astype("f8")
    total = max(1.0, deg.sum())
    labels = np.zeros(n, "i8")
    work, fresh = [(np.arange(n), np.arange(len(a)), 0)], 1
    place = np.zeros(n, "i8")
    while work:
        own, edges, level = work.pop()
        if len(own) < 2 * least or level >= depth:
            continue
        place[own] = np.arange(len(own))
        x, y = place[a[edges]], place[b[edges]]
        d = deg[own]
        inner = np.bincount(np.r_[x, y], minlength=len(own))
        row = inner - d * d.sum() / total
        shift = float((inner + d * d.sum() / total + np.abs(row)).max(initial=0)) / 2
        v = np.cos(np.arange(1, len(own) + 1) * 1.37)
        for _ in range(iterations):
            u = np.bincount(x, v[y], len(own)) + np.bincount(y, v[x], len(own)) - d * (d @ v) / total - row * v + shift * v
            size = np.linalg.norm(u)
            if size == 0:
                break
            u /= size
            if np.abs(u - v).max() < 1e-5:
                v = u
                break
            v = u
        side = v > 0
        s = np.where(side, 1.0, -1.0)
        gain = (2 * (s[x] * s[y]).sum() - (d @ s) ** 2 / total - row.sum()) / (2 * total)
        if gain <= 1e-9 or side.all() or not side.any():
            continue
        labels[own[side]] = fresh
        fresh += 1
        inside = side[x], side[y]
        work += [(own[side], edges[inside[0] & inside[1]], level + 1), (own[~side], edges[~inside[0] & ~inside[1]], level + 1)]
    return labels


def spectral_modularity(g: Graph, max_iter: int = 300) -> DataFrame:
    """Recursive division by the sign of the leading eigenvector of each set's modularity matrix, while modularity grows."""
    return in_one_task(g, lambda n, a, b: spectral_labels(n, a, b, iterations=max_iter))


def belief_propagation(g: Graph, objective: str = "modularity", k_grid: tuple[int, ...] | None = None, damping: float = 0.3, max_iter: int = 60, seed: int = 0) -> DataFrame:
    """Messages along edges; the number of groups is scanned upward as long as the found modularity grows.

    Without ``k_grid`` it grows by a factor of 1.3 from 2 on, with no largest number, until it is twice what was best.

    Numbers that are needed whatever the last of them gives are tried side by side, each in a task; the best is found as if
    they had been tried one after the other.

    ``modularity``: one coupling for equal groups. ``sbm``: a table of affinities, learned between the sweeps.
    """
    if objective not in ("modularity", "sbm"):
        raise ValueError("objective must be modularity or sbm")

    if g.m > ONE_TASK_EDGES:
        raise ValueError(f"{g.m} edges; this method runs in a task for each number of groups and takes at most {ONE_TASK_EDGES}")

    def run(key, left, right):
        k, ids = key[0].as_py(), np.sort(left["id"].to_numpy())
        a, b = (np.searchsorted(ids, right[c].to_numpy()) if right.num_rows else np.zeros(0, "i8") for c in ("src", "dst"))
        order = np.lexsort((b, a))  # edges come in any order
        a, b = a[order], b[order]
        deg = np.bincount(np.r_[a, b], minlength=len(ids)).astype("f8")
        labels = messages(len(ids), a, b, deg, k, objective, damping, max_iter, seed)
        vol = np.bincount(labels, deg, k)
        score = (labels[a] == labels[b]).mean() - ((vol / max(1.0, deg.sum())) ** 2).sum() if len(a) else 0.0
        return pa.table({"k": pa.array(np.full(len(ids), k), pa.int64()), "id": pa.array(ids, pa.int64()), "block": pa.array(np.asarray(labels, "i8")), "score": pa.array(np.full(len(ids), score))})

    best, groups, score, grid = g.nodes.select("id", F.lit(0).alias("block")), 1, 0.0, list(k_grid or scan(g.n))
    nodes, edges = g.nodes.select("id"), g.arcs.where("src < dst").select("src", "dst")
    while grid:
        some = side_by_side(grid, 2 * groups, 2 * g.m)
        grid = grid[len(some) :]
        each = F.explode(F.array(*[F.lit(k).cast("long") for k in some])).alias("k")
        left, right = (rows.select(each, "*").repartition(TRIAL_PARTS, "k").groupBy("k") for rows in (nodes, edges))
        found = written(left.cogroup(right).applyInArrow(run, "k long, id long, block long, score double"))
        told = {r["k"]: r for r in found.groupBy("k").agg(F.first("score").alias("score"), (F.max("block") + 1).alias("groups")).collect()}
        for k in some:  # in their order, as if tried one after the other
            if k not in told:
                continue
            if told[k]["score"] <= score + 1e-3:
                if k >= 2 * groups:
                    return named(best)
                continue
            best, groups, score = found.where(F.col("k") == k).select("id", "block"), told[k]["groups"], told[k]["score"]
    return named(best)


def side_by_side(grid: list[int], enough: int, arcs: int) -> list[int]:
    """The next numbers of groups to try: up to the first that can end the scan, as far as their messages leave room."""
    some: list[int] = []
    for k in grid:
        if some and (some[-1] >= max(enough, AT_ONCE) or 4 * arcs * (sum(some) + k) > MESSAGE_BYTES):
            break
        some.append(k)
    return some


def scan(most: int) -> Iterator[int]:
    k = 2
    while k <= most:
        yield k
        k = math.ceil(1.3 * k)


def messages(n: int, a: np.ndarray, b: np.ndarray, deg: np.ndarray, k: int, objective: str, damping: float, max_iter: int, seed: int) -> np.ndarray:
    """Each node's likeliest group. All messages are renewed at once in each sweep.

    Messages to a node lie side by side. A new one needs its sender's sum and the old one in the other direction alone, so
    that the two of each edge take each other's place in turn: one table of arcs and groups is all there is.
    """
    m = len(a)
    if not m:
        return np.zeros(n, "i8")
    to = np.r_[b, a]
    order = np.argsort(to, kind="stable")
    place = np.empty(2 * m, "i8")
    place[order] = np.arange(2 * m)
    back = place[(order + m) % (2 * m)]  # where the answer to each message lies
    end = to[order]
    bounds = np.searchsorted(end, np.arange(n + 1))
    one = np.flatnonzero(back > np.arange(2 * m))
    other = back[one]
    excess = max(1.5, (deg**2).mean() / deg.mean() - 1)
    beta = np.log(k / (np.sqrt(excess) - 1) + 1) if excess > 1 else 1.0
    step, turns = max(1, TURN // k), [0]
    psi = np.empty((2 * m, k), "f4")
    for at in range(0, 2 * m, step):
        rows = uniform_block(seed + k, order[at : at + step], k)
        psi[at : at + step] = rows / rows.sum(axis=1, keepdims=True)
    while turns[-1] < n:
        turns.append(max(turns[-1] + 1, int(np.searchsorted(bounds, bounds[turns[-1]] + step, "right")) - 1))
    belief = np.full((n, k), 1 / k, "f4")

    ones = np.ones(k, "f4")

    def shares(x: np.ndarray) -> np.ndarray:
        x /= (x @ ones)[:, None]
        return x

    table = np.ones((k, k)) + np.eye(k) * (np.exp(beta) - 1)
    for sweep in range(max_iter):
        change, joint = 0.0, np.zeros((k, k))
        learns = objective == "sbm" and sweep % 10 == 9
        field = deg @ belief
        away = -(beta if objective == "modularity" else 1.0) * (field if objective == "modularity" else field @ table / table.mean()) / deg.sum()
        narrow = table.astype("f4")

        def odds(rows: np.ndarray) -> np.ndarray:
            if objective == "sbm":
                return rows @ narrow
            out = rows * np.float32(np.exp(beta) - 1)
            out += np.float32(1)
            return out

        whole = (deg[:, None] * away).astype("f4")
        for first, last in zip(turns[:-1], turns[1:], strict=True):
            some = first + np.flatnonzero(np.diff(bounds[first : last + 1]))
            if len(some):
                pull = odds(psi[bounds[first] : bounds[last]])
                whole[some] += np.add.reduceat(np.log(pull, out=pull), bounds[some] - bounds[first], axis=0)
        whole -= whole.max(axis=1, keepdims=True)
        np.exp(whole, out=whole)
        belief = shares(whole.copy())
        for at in range(0, m, step):
            x, y = one[at : at + step], other[at : at + step]
            old_x, old_y = psi.take(x, axis=0), psi.take(y, axis=0)
            for sent, old, answer, sender in ((y, old_y, old_x, end[x]), (x, old_x, old_y, end[y])):
                new = shares(np.divide(whole.take(sender, axis=0), odds(answer)))
                if change < 1e-3:
                    change = float(np.abs(new - old).max())
                new *= np.float32(1 - damping)
                new += np.float32(damping) * old
                psi[sent] = new
        if learns:
            for at in range(0, m, step):
                joint += belief[a[at : at + step]].T @ belief[b[at : at + step]]
            joint = (joint + joint.T) / 2
            vol = deg @ belief
            learned = joint * 2 * deg.sum() / np.maximum(np.outer(vol, vol), 1e-9)
            table = 0.5 * table + 0.5 * np.maximum(learned / max(learned.mean(), 1e-9), 1e-3)
        if change < 1e-3:
            break
    return belief.argmax(axis=1)
