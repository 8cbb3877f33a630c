"""Graphs from the exact degree-corrected block model, and parameters of a benchmark.

The number of edges between nodes i and j is Poisson with rate theta_i theta_j omega(block i, block j). Pairs are
unordered; a node has no edge to itself.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.rng import hash01, mixed
from ..plans.state import fresh_folder, part_files, plainly_shared, settle, written

THETA_LOW, THETA_HIGH, THETA_POWER = 0.25, 3.0, 2.5
STRIP_EDGES = 200_000  # expected edges of one strip of a block pair
CELLS_UP_TO = 5_000
BROADCAST_NODES = 4_000_000  # 64 MB of ids and theta
GROUP_NODES = 2_000_000  # of blocks that lie in one file; a task holds two such groups
STRIPS_AT_ONCE = 256  # of two groups, in a task


@dataclass(frozen=True)
class Params:
    """``nodes``: (id, block INT, theta). ``omega``: (r, s, rate) with r <= s, a small list of K (K + 1) / 2 rows."""

    nodes: DataFrame
    omega: list[tuple[int, int, float]]

    def omega_df(self) -> DataFrame:
        return self.nodes.sparkSession.createDataFrame(self.omega, "r int, s int, rate double")


def theta_column(seed: int, node: Column, low: float = THETA_LOW, high: float = THETA_HIGH, power: float = THETA_POWER) -> Column:
    """A bounded power law by inversion, with mean 1 before rounding by the sample."""
    a, b = low ** (1 - power), high ** (1 - power)
    return F.pow(F.lit(a) + hash01(seed, node, 7) * (b - a), 1 / (1 - power)) / theta_mean(low, high, power)


def theta_mean(low: float = THETA_LOW, high: float = THETA_HIGH, power: float = THETA_POWER) -> float:
    return (1 - power) / (2 - power) * (high ** (2 - power) - low ** (2 - power)) / (high ** (1 - power) - low ** (1 - power))


def theta_grid(n: int = 128) -> np.ndarray:
    """Equally likely values of theta."""
    a, b = THETA_LOW ** (1 - THETA_POWER), THETA_HIGH ** (1 - THETA_POWER)
    return (a + (np.arange(n) + 0.5) / n * (b - a)) ** (1 / (1 - THETA_POWER)) / theta_mean()


def block_shares(k: int, heterogeneity: float, seed: int) -> np.ndarray:
    """Shares of the blocks; the largest is about ``heterogeneity`` times the smallest."""
    u = mixed(np.arange(1, k + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed)).astype("f8") / 2.0**64
    size = 1 + (heterogeneity - 1) * u
    return size / size.sum()


def benchmark_params(
    nodes: DataFrame, ratio: float = 2.5, heterogeneity: float = 3.0, mean_degree: float = 36.0, k: int | None = None, seed: int = 0, block: str | None = None, degree_corrected: bool = True, simple: bool = True, even: str = "blocks"
) -> Params:
    """Parameters over ``nodes`` (id and, if ``block`` names one, a column of integers to be used as true blocks).

    ``ratio``: edges within blocks to edges between them. Without ``k``, it is the floor of n ** 0.35. With ``simple``
    the rates are solved so that the ratio holds after repeated edges have been collapsed. ``even``: with ``blocks`` each
    block keeps the ratio, with ``totals`` one rate holds within all blocks, so that nodes of small blocks have fewer
    edges within and the ratio holds for the totals only.
    """
    if even not in ("blocks", "totals"):
        raise ValueError("even must be blocks or totals")
    if block is None:
        k = k or max(1, math.floor(nodes.count() ** 0.35))
        bounds = np.cumsum(block_shares(k, heterogeneity, seed))[:-1]

        def place(batches):
            for b in batches:
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.searchsorted(bounds, b.column(1).to_numpy(), "right").astype("i4"))], ["id", "block"])

        placed = nodes.select(F.col("id").cast("long").alias("id"), hash01(seed, F.col("id").cast("long"), 3).alias("draw")).mapInArrow(place, "id long, block int")
    else:
        placed = nodes.select(F.col("id").cast("long").alias("id"), F.col(block).cast("int").alias("block"))
    theta = theta_column(seed, F.col("id")) if degree_corrected else F.lit(1.0)
    placed = written(placed.withColumn("theta", theta))
    sums = sorted((r["block"], r["n"], r["t"], r["q"]) for r in placed.groupBy("block").agg(F.count(F.lit(1)).alias("n"), F.sum("theta").alias("t"), F.sum(F.col("theta") * F.col("theta")).alias("q")).collect())
    return Params(placed, solve_rates(sums, ratio, mean_degree, simple, degree_corrected, even))


def solve_rates(sums: list[tuple[int, int, float, float]], ratio: float, mean_degree: float, simple: bool, degree_corrected: bool, even: str = "blocks") -> list[tuple[int, int, float]]:
    n = sum(s[1] for s in sums)
    edges = n * mean_degree / 2
    within, between = edges * ratio / (1 + ratio), edges / (1 + ratio)
    inside = sum((t * t - q) / 2 for _, _, t, q in sums)
    total = sum(s[2] for s in sums)
    across = (total**2 - sum(t * t for _, _, t, _ in sums)) / 2
    grid = theta_grid() if degree_corrected else np.ones(1)
    product = np.outer(grid, grid)

    def rate(target: float, mass: float) -> float:
        if mass <= 0:
            return 0.0
        if not simple or target >= mass * 1e6:
            return target / mass
        low, high = 0.0, 4 * target / mass + 1e-12
        while mass * (1 - np.exp(-product * high)).mean() / product.mean() < target and high < 1e6:
            high *= 2
        for _ in range(60):
            mid = (low + high) / 2
            low, high = (mid, high) if mass * (1 - np.exp(-product * mid)).mean() / product.mean() < target else (low, mid)
        return high

    b = rate(between, across)
    if even == "totals":
        own = [rate(within, inside)] * len(sums)
    else:
        own = [rate(within * t / total, (t * t - q) / 2) for _, _, t, q in sums]
    return [(r[0], s[0], own[i] if r[0] == s[0] else b) for i, r in enumerate(sums) for s in sums[i:]]


def rates_df(params: Params) -> DataFrame:
    """(r, s, cells, mass): the pairs of nodes of each block pair and their summed rates, without listing them."""
    sums = params.nodes.groupBy("block").agg(F.count(F.lit(1)).alias("n"), F.sum("theta").alias("t"), F.sum(F.col("theta") * F.col("theta")).alias("q"))
    left, right = (sums.select(F.col("block").alias(c), *[F.col(x).alias(f"{x}_{c}") for x in ("n", "t", "q")]) for c in ("r", "s"))
    both = F.broadcast(params.omega_df()).join(left, "r").join(right, "s")
    same = F.col("r") == F.col("s")
    cells = F.when(same, F.col("n_r") * (F.col("n_r") - 1) / 2).otherwise(F.col("n_r") * F.col("n_s"))
    mass = F.when(same, (F.col("t_r") * F.col("t_r") - F.col("q_r")) / 2).otherwise(F.col("t_r") * F.col("t_s"))
    return both.select("r", "s", cells.cast("long").alias("cells"), (mass * F.col("rate")).alias("mass"))


def prefix(params: Params) -> DataFrame:
    """(block, pos, id, theta, before, upto): nodes of a block by id, with prefix sums of theta."""
    from pyspark.sql import Window

    w = Window.partitionBy("block").orderBy("id")
    upto = F.sum("theta").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return params.nodes.select("block", (F.row_number().over(w) - 1).alias("pos"), "id", "theta", (upto - F.col("theta")).alias("before"), upto.alias("upto"))


@dataclass(frozen=True)
class CellMass:
    """Summed rates over the cells of a block pair's table, in row order: prefix sums are made once, each sum is O(1).

    Two blocks: rows and columns by id. One block (``theta_s`` None): the pairs i < j, where a place is found by the
    inverse of the triangle's row lengths.
    """

    theta_r: np.ndarray
    upto_r: np.ndarray
    upto_s: np.ndarray
    rows: np.ndarray | None
    rate: float

    @staticmethod
    def of(theta_r: np.ndarray, theta_s: np.ndarray | None, rate: float) -> CellMass:
        upto = np.r_[0.0, np.cumsum(theta_r)]
        if theta_s is not None:
            return CellMass(theta_r, upto, np.r_[0.0, np.cumsum(theta_s)], None, rate)
        return CellMass(theta_r, upto, upto, np.r_[0.0, np.cumsum(theta_r * (upto[-1] - upto[1:]))], rate)

    def before(self, cell: int) -> float:
        """The mass of the first ``cell`` cells."""
        n = len(self.theta_r)
        if self.rows is None:
            row, column = divmod(cell, len(self.upto_s) - 1)
            partial = self.theta_r[row] * self.upto_s[column] if row < n else 0.0
            return self.rate * (self.upto_r[row] * self.upto_s[-1] + partial)
        if cell >= n * (n - 1) // 2:
            return self.rate * self.rows[-1]
        # Rows before row i hold i (2n - 1 - i) / 2 cells.
        row = (2 * n - 1 - math.isqrt((2 * n - 1) ** 2 - 8 * cell)) // 2
        while row * (2 * n - 1 - row) // 2 > cell:
            row -= 1
        while (row + 1) * (2 * n - 2 - row) // 2 <= cell:
            row += 1
        column = row + 1 + cell - row * (2 * n - 1 - row) // 2
        return self.rate * (self.rows[row] + self.theta_r[row] * (self.upto_r[column] - self.upto_r[row + 1]))


def range_sum(theta_r: np.ndarray, theta_s: np.ndarray | None, rate: float, first: int, last: int) -> float:
    """The summed rate of cells ``first`` to ``last`` (inclusive) of a block pair's table; ``theta_s`` None: the pairs i < j inside a block."""
    mass = CellMass.of(theta_r, theta_s, rate)
    return mass.before(last + 1) - mass.before(first)


def cells(params: Params, seed: int = 0, limit: int = CELLS_UP_TO) -> DataFrame:
    """(src, dst): each pair of nodes by its own uniform. The reference law, for small graphs only: it looks at all pairs."""
    if params.nodes.count() > limit:
        raise ValueError(f"cells() looks at all pairs; use skip() or split() beyond {limit} nodes")
    a, b = (params.nodes.select(F.col("id").alias(e), F.col("block").alias(f"b_{e}"), F.col("theta").alias(f"t_{e}")) for e in ("src", "dst"))
    both = a.join(b, F.col("src") < F.col("dst")).join(F.broadcast(params.omega_df()), (F.least("b_src", "b_dst") == F.col("r")) & (F.greatest("b_src", "b_dst") == F.col("s")))
    return both.where(hash01(seed, F.col("src"), F.col("dst")) < 1 - F.exp(-F.col("t_src") * F.col("t_dst") * F.col("rate"))).select("src", "dst")


def block_arrays(params: Params) -> DataFrame:
    """(block, ids, theta): each block's nodes by id. A block is held by the task that draws its strips."""
    rows = F.array_sort(F.collect_list(F.struct("id", "theta")))
    return params.nodes.groupBy("block").agg(rows.alias("x")).select("block", F.col("x.id").alias("ids"), F.col("x.theta").alias("theta"))


def prefix_sums(x: np.ndarray) -> np.ndarray:
    out = np.zeros(len(x) + 1)
    np.cumsum(x, out=out[1:])
    return out


def draw_strip(ids_r: np.ndarray, theta_r: np.ndarray, ids_s: np.ndarray, theta_s: np.ndarray, rate: float, first: int, last: int, same: bool, rng: np.random.Generator, upto: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Edges and weights of rows ``first`` to ``last`` - 1 of a block pair, by jumps over the cumulative rate.

    Jumps between hits are exponential in the summed rate; a jump's cell is found in the prefix sums of the rows and,
    within the row, of the columns. A cell that is hit gets the rest of its Poisson law from further hits in it, so the
    weights have the law of the model given that the cell is not empty. ``upto``: the prefix sums of ``theta_s``.
    """
    upto = prefix_sums(theta_s) if upto is None else upto
    own = theta_r[first:last]
    start = upto[first + 1 : last + 1] if same else None
    mass = rate * own * (np.maximum(0.0, upto[-1] - start) if same else upto[-1])
    bound = prefix_sums(mass)
    hits, at = [], 0.0
    while at < bound[-1]:
        steps = at + np.cumsum(rng.exponential(size=max(64, int(1.1 * (bound[-1] - at)) + 16)))
        at = steps[-1]
        hits.append(steps[steps < bound[-1]])
    place = np.concatenate(hits) if hits else np.zeros(0)
    row = np.minimum(np.searchsorted(bound, place, "right") - 1, len(own) - 1)
    inside = (place - bound[row]) / np.maximum(rate * own[row], 1e-300)
    column = np.searchsorted(upto, start[row] + inside if same else inside, "right") - 1
    column = np.clip(column, (first + row + 1) if same else 0, len(ids_s) - 1)
    # Places rise, and so do their cells.
    cell = row.astype("i8") * len(ids_s) + column
    starts = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]]) if len(cell) else np.zeros(0, "i8")
    cell, weight = cell[starts], np.diff(np.r_[starts, len(cell)])
    return ids_r[first + cell // len(ids_s)], ids_s[cell % len(ids_s)], weight


def plan_strips(params: Params, strip_edges: int = STRIP_EDGES) -> list[tuple[int, int, float, int, int]]:
    """(r, s, rate, first row, last row) of strips with about ``strip_edges`` expected edges; what strips hold is disjoint."""
    out = []
    rate = {(r, s): x for r, s, x in params.omega}
    sizes = {r["block"]: r["n"] for r in params.nodes.groupBy("block").agg(F.count(F.lit(1)).alias("n")).collect()}
    for row in rates_df(params).orderBy("r", "s").collect():
        r, s, n = row["r"], row["s"], sizes[row["r"]]
        strips = max(1, min(n, math.ceil(row["mass"] / strip_edges)))
        out += [(r, s, rate[r, s], n * k // strips, n * (k + 1) // strips) for k in range(strips)]
    return out


def in_groups(params: Params) -> tuple[str, dict[int, int]]:
    """Nodes in files of the shared folder, ``g=k`` for group k of neighbouring blocks with up to ``GROUP_NODES`` nodes (a larger
    block is a group of its own), and each block's group."""
    spark = params.nodes.sparkSession
    group: dict[int, int] = {}
    at, held = 0, 0
    for row in params.nodes.groupBy("block").agg(F.count(F.lit(1)).alias("n")).orderBy("block").collect():
        if held and held + row["n"] > GROUP_NODES:
            at, held = at + 1, 0
        group[row["block"]] = at
        held += row["n"]
    folder = fresh_folder(spark)
    code = F.broadcast(spark.createDataFrame(list(group.items()), "block int, g int"))
    dealt = params.nodes.join(code, "block").select("g", "block", "id", "theta").repartitionById(at + 1, F.col("g")).sortWithinPartitions("g", "block", "id")
    dealt.write.option("compression", "zstd").partitionBy("g").parquet(folder)
    return folder, group


def read_group(folder: str, k: int) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Ids, theta and its prefix sums of each block of a group, by id."""
    columns = [[], [], []]
    for file in part_files(folder, "g", k):
        table = pq.ParquetFile(file).read(columns=["block", "id", "theta"])
        for own, c in zip(columns, table.columns, strict=True):
            own.append(c.to_numpy())
    block, ids, theta = (np.concatenate(c) for c in columns)
    bounds = np.flatnonzero(np.r_[True, block[1:] != block[:-1], True])
    if len(np.unique(block[bounds[:-1]])) < len(bounds) - 1:
        order = np.lexsort((ids, block))  # a group that has come in several files
        block, ids, theta = block[order], ids[order], theta[order]
        bounds = np.flatnonzero(np.r_[True, block[1:] != block[:-1], True])
    return {int(block[a]): (ids[a:b], theta[a:b], prefix_sums(theta[a:b])) for a, b in zip(bounds[:-1], bounds[1:], strict=True)}


def skip(params: Params, seed: int = 0, strip_edges: int = STRIP_EDGES, broadcast_nodes: int = BROADCAST_NODES) -> DataFrame:
    """(src, dst, weight) by jumps, strip by strip. A strip's randomness depends on the seed and its place alone.

    Up to ``broadcast_nodes`` nodes, ids and theta of all of them go to each task; beyond that, they lie in files of the
    shared folder, of which a task reads the two that hold the blocks of its strips. Where Python cannot open that
    folder, the nodes of a strip's two blocks are joined to it. Edges are the same.
    """
    spark = params.nodes.sparkSession
    planned = plan_strips(params, strip_edges)
    strips = spark.createDataFrame(planned, "r int, s int, rate double, first long, last long").repartition(spark.sparkContext.defaultParallelism * 2, "r", "s", "first")
    kind = "src long, dst long, weight long"

    def drawn(r, s, rate, first, last, own, upto=None):
        src, dst, weight = draw_strip(*own, rate, first, last, r == s, np.random.default_rng([seed, r, s, first]), upto)
        return pa.RecordBatch.from_arrays([pa.array(np.minimum(src, dst)), pa.array(np.maximum(src, dst)), pa.array(weight)], ["src", "dst", "weight"])

    if params.nodes.count() <= broadcast_nodes:
        table = params.nodes.select("block", "id", "theta").toArrow().sort_by([("block", "ascending"), ("id", "ascending")])
        block, ids, theta = (table[c].to_numpy() for c in ("block", "id", "theta"))
        starts = {int(x): (int(a), int(b)) for x, a, b in zip(*np.unique(block, return_index=True), np.r_[np.unique(block, return_index=True)[1][1:], len(block)], strict=True)}
        shared = spark.sparkContext.broadcast((ids, theta))

        def here(batches):
            ids, theta = shared.value
            for batch in batches:
                for r, s, rate, first, last in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                    (a, b), (c, d) = starts[r], starts[s]
                    yield drawn(r, s, rate, first, last, (ids[a:b], theta[a:b], ids[c:d], theta[c:d]))

        return strips.mapInArrow(here, kind)
    if plainly_shared(spark):
        folder, group = in_groups(params)
        tiles: dict[tuple[int, int], list] = {}
        for strip in planned:
            tiles.setdefault((group[strip[0]], group[strip[1]]), []).append(strip)
        tasks = [tile[k : k + STRIPS_AT_ONCE] for _, tile in sorted(tiles.items()) for k in range(0, len(tile), STRIPS_AT_ONCE)]
        rows = [(t, group[x[0]], group[x[1]], *x) for t, task in enumerate(tasks) for x in task]
        work = spark.createDataFrame(rows, "t int, i int, j int, r int, s int, rate double, first long, last long").repartitionById(max(1, len(tasks)), F.col("t"))

        def from_files(batches):
            held: dict[int, dict] = {}
            for batch in batches:
                for _, i, j, r, s, rate, first, last in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                    if not held.keys() >= {i, j}:
                        held = {k: held.get(k) or read_group(folder, k) for k in {i, j}}
                    yield drawn(r, s, rate, first, last, (*held[i][r][:2], *held[j][s][:2]), held[j][s][2])

        return work.mapInArrow(from_files, kind)
    arrays = block_arrays(params)
    left, right = (arrays.select(F.col("block").alias(c), F.col("ids").alias(f"ids_{c}"), F.col("theta").alias(f"theta_{c}")) for c in ("r", "s"))
    work = strips.join(left, "r").join(right, "s").select("r", "s", "rate", "first", "last", "ids_r", "theta_r", "ids_s", "theta_s")

    def run(batches):
        for batch in batches:
            for k in range(batch.num_rows):
                yield drawn(*[batch.column(c)[k].as_py() for c in range(5)], [batch.column(c)[k].values.to_numpy() for c in range(5, 9)])

    return work.mapInArrow(run, kind)


def poisson_totals(params: Params, seed: int = 0) -> list[tuple[int, int, int]]:
    return [(row["r"], row["s"], int(np.random.default_rng([seed, row["r"], row["s"], 1 << 20]).poisson(row["mass"]))) for row in rates_df(params).orderBy("r", "s").collect()]


def split(params: Params, seed: int = 0, chunk: int = 10_000) -> DataFrame:
    """(src, dst, weight) with the same law, as sets: each block pair's total is Poisson, and both ends of each edge are
    drawn in proportion to theta. Ends come by a join on ranges of the cumulative theta, cut into equal buckets.

    Inside a block the ordered pairs, loops among them, are drawn at half the rate each way; loops are then dropped.
    """
    spark = params.nodes.sparkSession
    inside = {r["block"]: r["t"] for r in params.nodes.groupBy("block").agg(F.sum("theta").alias("t")).collect()}
    totals = [(r, s, n) for r, s, n in poisson_totals(params, seed) if r != s]
    rate = {(r, s): x for r, s, x in params.omega}
    totals += [(r, r, int(np.random.default_rng([seed, r, r, 1 << 21]).poisson(rate[r, r] * t * t / 2))) for r, t in sorted(inside.items()) if (r, r) in rate]
    parts = [(r, s, at, min(chunk, n - at)) for r, s, n in totals for at in range(0, n, chunk)]
    drawn = spark.createDataFrame(parts, "r int, s int, at long, n long").repartition("r", "s", "at").select("r", "s", F.explode(F.sequence(F.col("at"), F.col("at") + F.col("n") - 1)).alias("k"))
    table = prefix(params)
    size = table.groupBy("block").agg(F.max("upto").alias("whole"), F.count(F.lit(1)).alias("n"))
    spans = table.join(F.broadcast(size), "block").withColumn("width", F.col("whole") / F.col("n"))
    spans = spans.select("block", "id", "before", "upto", F.explode(F.sequence(F.floor(F.col("before") / F.col("width")), F.floor(F.col("upto") / F.col("width")))).alias("bucket"))

    def ends(rows: DataFrame, block: str, stream: int, out: str) -> DataFrame:
        aim = rows.join(F.broadcast(size.withColumnRenamed("block", block)), block).withColumn("aim", hash01(seed, F.col("r"), F.col("s"), F.col("k"), stream) * F.col("whole"))
        aim = aim.withColumn("bucket", F.floor(F.col("aim") / (F.col("whole") / F.col("n")))).drop("whole", "n")
        found = spans.select(F.col("block").alias(block), F.col("id").alias(out), "before", "upto", "bucket")
        # Spans are all nodes: never by way of the driver.
        return aim.join(found.hint("merge"), [block, "bucket"]).where("aim >= before and aim < upto").drop("bucket", "aim", "before", "upto")

    both = ends(ends(drawn, "r", 0, "x"), "s", 1, "y").where("x <> y")
    return both.groupBy(F.least("x", "y").alias("src"), F.greatest("x", "y").alias("dst")).agg(F.count(F.lit(1)).alias("weight"))


def rewired(params: Params, seed: int = 0, sweeps: int = 5) -> DataFrame:
    """(src, dst): an approximate sampler for comparison. It starts from a graph with the model's degrees but no blocks and
    swaps the ends of disjoint pairs of edges, accepting by the ratio of rates; few sweeps leave it biased."""
    flat = Params(params.nodes.withColumn("block", F.lit(0)), [(0, 0, sum(r["mass"] for r in rates_df(params).collect()) / max(1e-12, flat_mass(params)))])
    edges = settle(skip(flat, seed).select("src", "dst"))
    blocks = params.nodes.select("id", "block")
    omega = F.broadcast(params.omega_df())

    def rates(df: DataFrame, a: str, b: str, out: str) -> DataFrame:
        return df.join(omega, (F.least(f"b_{a}", f"b_{b}") == F.col("r")) & (F.greatest(f"b_{a}", f"b_{b}") == F.col("s"))).withColumnRenamed("rate", out).drop("r", "s")

    for k in range(sweeps):
        placed = edges.join(blocks.select(F.col("id").alias("src"), F.col("block").alias("b_src")), "src").join(blocks.select(F.col("id").alias("dst"), F.col("block").alias("b_dst")), "dst")
        cell = F.pmod(F.xxhash64(F.lit(seed), F.lit(k), "src", "dst"), F.lit(max(1, edges.count() // 2)))
        ranked = placed.withColumn("cell", cell).groupBy("cell").agg(F.array_sort(F.collect_list(F.struct("src", "dst", "b_src", "b_dst"))).alias("e"))
        pairs = ranked.where("size(e) >= 2").select("cell", *[F.col("e")[i][c].alias(f"{c}_{i}") for i in (0, 1) for c in ("src", "dst", "b_src", "b_dst")], F.slice("e", 3, 1 << 20).alias("rest"))
        named = pairs.select("cell", "rest", *[F.col(f"{c}_{i}").alias(f"{n}{i}") for i in (0, 1) for c, n in (("src", "s"), ("dst", "d"))], *[F.col(f"b_{c}_{i}").alias(f"b_{n}{i}") for i in (0, 1) for c, n in (("src", "s"), ("dst", "d"))])
        rated = rates(rates(rates(rates(named, "s0", "d0", "r00"), "s1", "d1", "r11"), "s0", "d1", "r01"), "s1", "d0", "r10")
        take = (hash01(seed, F.col("cell"), F.lit(k)) < F.col("r01") * F.col("r10") / (F.col("r00") * F.col("r11"))) & (F.col("s0") != F.col("d1")) & (F.col("s1") != F.col("d0"))
        new = rated.select(F.explode(F.concat(F.when(take, F.array(F.struct(F.col("s0").alias("src"), F.col("d1").alias("dst")), F.struct(F.col("s1").alias("src"), F.col("d0").alias("dst")))).otherwise(F.array(F.struct(F.col("s0").alias("src"), F.col("d0").alias("dst")), F.struct(F.col("s1").alias("src"), F.col("d1").alias("dst")))), F.transform("rest", lambda x: F.struct(x["src"].alias("src"), x["dst"].alias("dst"))))).alias("e")).select("e.src", "e.dst")
        single = ranked.where("size(e) = 1").select(F.col("e")[0]["src"].alias("src"), F.col("e")[0]["dst"].alias("dst"))
        edges = settle(new.unionByName(single).select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")))
    return edges.distinct()


def flat_mass(params: Params) -> float:
    row = params.nodes.agg(F.sum("theta").alias("t"), F.sum(F.col("theta") * F.col("theta")).alias("q")).first()
    return (row["t"] ** 2 - row["q"]) / 2


def sample(params: Params, method: str = "skip", seed: int = 0, simple: bool = True) -> DataFrame:
    """Edges by one of the samplers; ``simple`` leaves the weights out."""
    made = {"skip": skip, "split": split, "cells": cells, "rewired": rewired}[method](params, seed)
    return made.select("src", "dst") if simple else made
