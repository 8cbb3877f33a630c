"""Splitting a set of vectors in two by 2-means."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.rng import uniform_block

INITS = ("far", "kmeans++", "axis")
ONE_TASK_ROWS = 32_768  # vectors of a set that goes to one task; larger ones are summed up where they lie


def starts(z: np.ndarray, ids: np.ndarray, init: str, seed: int) -> np.ndarray:
    """Two first centres. Ties go to the earlier row."""
    if init == "far":
        one = ((z - z.mean(axis=0)) ** 2).sum(axis=1).argmax()
        two = ((z - z[one]) ** 2).sum(axis=1).argmax()
        return np.stack([z[one], z[two]])
    if init == "kmeans++":
        u = uniform_block(seed, ids, 2)
        one = u[:, 0].argmin()
        far = ((z - z[one]) ** 2).sum(axis=1)
        with np.errstate(divide="ignore"):
            two = np.where(far > 0, -np.log(u[:, 1]) / np.where(far > 0, far, 1), np.inf).argmin()  # drawn with chance in proportion to far
        return np.stack([z[one], z[two]])
    if init == "axis":
        centre = z.mean(axis=0)
        axis = principal((z - centre).T @ (z - centre), seed)
        right = (z - centre) @ axis > 0
        if right.all() or not right.any():
            return np.stack([centre, centre])
        return np.stack([z[~right].mean(axis=0), z[right].mean(axis=0)])
    raise ValueError(f"init must be one of {INITS}")


def principal(cov: np.ndarray, seed: int) -> np.ndarray:
    axis = np.cos(np.arange(1, len(cov) + 1) * (seed + 1.0))
    for _ in range(50):
        axis = cov @ axis
        size = np.linalg.norm(axis)
        if size == 0:
            break
        axis /= size
    return axis


def plane(centres: np.ndarray) -> tuple[np.ndarray, float]:
    """w, b: a vector is nearer to the second centre where w . z > b; ties are with the first."""
    w = centres[1] - centres[0]
    return w, float((centres[1] ** 2).sum() - (centres[0] ** 2).sum()) / 2


def fit(z: np.ndarray, ids: np.ndarray, max_iter: int = 100, n_init: int = 1, init: str = "axis", seed: int = 0, rows: int = ONE_TASK_ROWS) -> tuple[np.ndarray, float]:
    """The plane between the halves of a set that is in memory: the best run on all its vectors.

    Rows are taken in order of id, so the result does not depend on how they are stored; ``two_means``, where ``rows``
    says which sets are summed up by jobs, gives the same planes.
    """
    order = np.argsort(ids, kind="stable")
    return best_run(z[order].astype("f8"), ids[order], max_iter, n_init, init, seed)


def centres_of(one: np.ndarray, n1: int, whole: np.ndarray, n: int) -> np.ndarray:
    return np.stack([(whole - one) / (n - n1), one / n1])


def best_run(z: np.ndarray, ids: np.ndarray, max_iter: int, n_init: int, init: str, seed: int) -> tuple[np.ndarray, float]:
    """The plane with the least squared error of ``n_init`` runs; the first starts as ``init`` says, others from drawn points."""
    if not len(z):
        return np.zeros(z.shape[1]), 0.0
    squares, whole = float((z**2).sum()), z.sum(axis=0)
    best, least = plane(np.stack([z[0], z[0]])), np.inf
    for run in range(n_init):
        centres = starts(z, ids, init if run == 0 else "kmeans++", seed + run)
        old = None
        for _ in range(max_iter):
            w, b = plane(centres)
            side = z @ w > b
            n = int(side.sum())
            if n in (0, len(z)) or (old is not None and (side == old).all()):
                break
            old = side
            centres = centres_of(side @ z, n, whole, len(z))
        w, b = plane(centres)
        side = z @ w > b
        n = int(side.sum())
        if 0 < n < len(z):
            one = side @ z
            zero = whole - one
            error = squares - (one**2).sum() / n - (zero**2).sum() / (len(z) - n)
            if error < least - 1e-12:
                best, least = (w, b), error
    return best


def two_means(assign: DataFrame, sizes: dict[str, int], max_iter: int = 100, n_init: int = 1, init: str = "axis", seed: int = 0, rows: int = ONE_TASK_ROWS) -> dict[str, tuple[np.ndarray, float]]:
    """The planes of all sets of ``assign`` (path, id, v), whose sizes are given, as ``fit`` makes them.

    Sets of up to ``rows`` vectors go to a task each. All larger ones are handled at once, in one job a step; tasks send
    sums, one vector for each set and run. Either way all vectors of a set are in its first centres and in each step.
    """
    small = {p for p, n in sizes.items() if n <= rows}

    def mine(paths: set[str]) -> DataFrame:
        wanted = F.broadcast(assign.sparkSession.createDataFrame([(p,) for p in sorted(paths)], "path string"))
        return assign.join(wanted, "path").select("path", "id", "v")

    def whole(key, table):
        ids = table["id"].to_numpy()
        order = np.argsort(ids, kind="stable")
        z = table["v"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)[order].astype("f8")
        w, b = best_run(z, ids[order], max_iter, n_init, init, seed)
        return pa.table({"path": [key[0].as_py()], "w": pa.array([w.tolist()], pa.list_(pa.float64())), "b": [b]})

    planes = {}
    if small:
        found = mine(small).groupBy("path").applyInArrow(whole, "path string, w array<double>, b double")
        planes = {r["path"]: (np.array(r["w"]), r["b"]) for r in found.collect()}
    if len(small) < len(sizes):
        planes |= best_runs(mine(set(sizes) - small), set(sizes) - small, max_iter, n_init, init, seed)
    return planes


def best_runs(mine: DataFrame, paths: set[str], max_iter: int, n_init: int, init: str, seed: int) -> dict[str, tuple[np.ndarray, float]]:
    """As ``best_run`` for each set of ``mine`` (path, id, v), by jobs over all vectors. Runs of all sets go side by side."""
    first = mine.select(F.size("v").alias("width")).first()
    if first is None:
        return {}
    flat = np.zeros(first["width"]), 0.0
    planes = started(mine, paths, n_init, init, seed, flat)
    old: dict[tuple[str, int], tuple[np.ndarray, float]] = {}
    best, most = dict.fromkeys(paths, flat), dict.fromkeys(paths, -np.inf)
    ended: dict[tuple[str, int], float] = {}  # the squares between the halves that a run has come to
    going = set(planes)
    for step in range(max_iter + 1):
        if not going:
            break
        for key, n1, one, n, whole, moved in lloyd_sums(mine, {k: planes[k] for k in going}, old):
            if n1 in (0, n):
                going.discard(key)
            elif step == max_iter or step and not moved:
                ended[key] = float((one**2).sum() / n1 + ((whole - one) ** 2).sum() / (n - n1))
                going.discard(key)
            else:
                old[key] = planes[key]
                planes[key] = plane(centres_of(one, n1, whole, n))
    for key in sorted(ended):
        if ended[key] > most[key[0]] + 1e-12:
            best[key[0]], most[key[0]] = planes[key], ended[key]
    return best


def started(mine: DataFrame, paths: set[str], n_init: int, init: str, seed: int, flat: tuple[np.ndarray, float]) -> dict[tuple[str, int], tuple[np.ndarray, float]]:
    """The planes of ``starts`` for each (path, run); the first run starts as ``init`` says, others from drawn points."""
    if init not in INITS:
        raise ValueError(f"init must be one of {INITS}")
    firsts = set() if init == "kmeans++" else {(p, 0) for p in paths}
    drawn = {(p, k) for p in paths for k in range(n_init)} - firsts
    planes = {}
    if firsts:
        centres = {key: whole / n for key, _, _, n, whole, _ in lloyd_sums(mine, dict.fromkeys(firsts, flat), {})}
    if firsts and init == "far":
        one = leaders(mine, firsts, lambda key, ids, z: ((z - centres[key]) ** 2).sum(axis=1))
        two = leaders(mine, firsts, lambda key, ids, z: ((z - one[key]) ** 2).sum(axis=1))
        planes |= {k: plane(np.stack([one[k], two[k]])) for k in firsts}
    elif firsts:
        axes = principal_axes(mine, {p: centres[p, 0] for p in paths}, seed)
        across = {(p, 0): (axis, float(axis @ centres[p, 0])) for p, axis in axes.items()}
        for key, n1, one, n, whole, _ in lloyd_sums(mine, across, {}):
            planes[key] = flat if n1 in (0, n) else plane(centres_of(one, n1, whole, n))
    if drawn:
        at = leaders(mine, drawn, lambda key, ids, z: -uniform_block(seed + key[1], ids, 2)[:, 0])

        def chance(key, ids, z):
            far = ((z - at[key]) ** 2).sum(axis=1)
            with np.errstate(divide="ignore"):
                return -np.where(far > 0, -np.log(uniform_block(seed + key[1], ids, 2)[:, 1]) / np.where(far > 0, far, 1), np.inf)

        other = leaders(mine, drawn, chance)
        planes |= {k: plane(np.stack([at[k], other[k]])) for k in drawn}
    return planes


def by_set(batch: pa.RecordBatch):
    """(path, ids, vectors) of each set in a batch (path, id, v)."""
    if batch.num_rows:
        code = batch.column(0).dictionary_encode()
        own, ids = code.indices.to_numpy(), batch.column(1).to_numpy()
        z = batch.column(2).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
        for c, path in enumerate(code.dictionary.to_pylist()):
            yield path, ids[own == c], z[own == c].astype("f8")


def runs_of(keys) -> dict[str, list[tuple[str, int]]]:
    out: dict[str, list[tuple[str, int]]] = {}
    for key in sorted(keys):
        out.setdefault(key[0], []).append(key)
    return out


def leaders(mine: DataFrame, keys: set[tuple[str, int]], score) -> dict[tuple[str, int], np.ndarray]:
    """For each (path, run), the vector where ``score(key, ids, z)`` is largest; of equal ones, that of the least id."""
    runs = runs_of(keys)

    def best(batches):
        held: dict[tuple[str, int], tuple] = {}
        for batch in batches:
            for path, ids, z in by_set(batch):
                for key in runs.get(path, ()):
                    value = score(key, ids, z)
                    top = np.flatnonzero(value == value.max())
                    k = top[ids[top].argmin()]
                    if key not in held or (value[k], -ids[k]) > held[key][:2]:
                        held[key] = float(value[k]), -int(ids[k]), z[k].tobytes()
        if held:
            found = sorted(held)
            yield pa.RecordBatch.from_arrays(
                [pa.array([p for p, _ in found]), pa.array([k for _, k in found], pa.int32()), pa.array([held[k][0] for k in found]), pa.array([held[k][1] for k in found], pa.int64()), pa.array([held[k][2] for k in found], pa.binary())],
                ["path", "run", "value", "near", "v"],
            )

    found = mine.mapInArrow(best, "path string, run int, value double, near long, v binary").groupBy("path", "run").agg(F.max_by("v", F.struct("value", "near")).alias("v"))
    return {(r["path"], r["run"]): np.frombuffer(r["v"], "f8") for r in found.collect()}


def principal_axes(mine: DataFrame, centres: dict[str, np.ndarray], seed: int) -> dict[str, np.ndarray]:
    """The principal axis of each set. Products are added up in as many tasks as run at once, so that few tables are moved."""
    width = len(next(iter(centres.values())))
    upper = np.triu_indices(width)

    def products(batches):
        held: dict[str, np.ndarray] = {}
        for batch in batches:
            for path, _, z in by_set(batch):
                z -= centres[path]
                held.setdefault(path, np.zeros((width, width)))
                held[path] += z.T @ z
        for path in sorted(held):
            yield pa.RecordBatch.from_arrays([pa.array([path]), pa.array([held[path][upper].tobytes()], pa.binary())], ["path", "cov"])

    def axis(key, table):
        cov = np.zeros((width, width))
        cov[upper] = sum(np.frombuffer(x, "f8") for x in sorted(table["cov"].to_pylist()))
        cov.T[upper] = cov[upper]
        return pa.table({"path": [key[0].as_py()], "axis": pa.array([principal(cov, seed).tobytes()], pa.binary())})

    few = mine.coalesce(max(1, mine.sparkSession.sparkContext.defaultParallelism))
    found = few.mapInArrow(products, "path string, cov binary").groupBy("path").applyInArrow(axis, "path string, axis binary")
    return {r["path"]: np.frombuffer(r["axis"], "f8") for r in found.collect()}


def lloyd_sums(mine: DataFrame, planes: dict[tuple[str, int], tuple[np.ndarray, float]], old: dict[tuple[str, int], tuple[np.ndarray, float]]):
    """((path, run), n1, sum1, n, sum, moved) for each plane of a set of ``mine`` (path, id, v): number and sum of what is
    beyond it, and of all, and how many vectors were on the other side of the ``old`` plane."""
    runs = runs_of(planes)

    def sums(batches):
        held: dict[tuple[str, int], list] = {}
        for batch in batches:
            for path, _, z in by_set(batch):
                whole = z.sum(axis=0)
                for key in runs.get(path, ()):
                    w, b = planes[key]
                    side = z @ w > b
                    x = held.setdefault(key, [0, np.zeros(z.shape[1]), 0, np.zeros(z.shape[1]), 0])
                    x[0] += int(side.sum())
                    x[1] += side @ z
                    x[2] += len(z)
                    x[3] += whole
                    if key in old:
                        x[4] += int((side != (z @ old[key][0] > old[key][1])).sum())
        if held:
            keys = sorted(held)
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([p for p, _ in keys]), pa.array([k for _, k in keys], pa.int32()), pa.array([held[k][0] for k in keys]), pa.array([held[k][1].tobytes() for k in keys], pa.binary()),
                    pa.array([held[k][2] for k in keys]), pa.array([held[k][3].tobytes() for k in keys], pa.binary()), pa.array([held[k][4] for k in keys]),
                ],
                ["path", "run", "n1", "one", "n", "whole", "moved"],
            )

    def total(key, table):
        one, whole = (sum(np.frombuffer(x, "f8") for x in sorted(table[c].to_pylist())) for c in ("one", "whole"))
        n1, n, moved = ([sum(table[c].to_pylist())] for c in ("n1", "n", "moved"))
        return pa.table({"path": [key[0].as_py()], "run": pa.array([key[1].as_py()], pa.int32()), "n1": n1, "one": pa.array([one.tobytes()], pa.binary()), "n": n, "whole": pa.array([whole.tobytes()], pa.binary()), "moved": moved})

    shape = "path string, run int, n1 long, one binary, n long, whole binary, moved long"
    for r in mine.mapInArrow(sums, shape).groupBy("path", "run").applyInArrow(total, shape).collect():
        yield (r["path"], r["run"]), r["n1"], np.frombuffer(r["one"], "f8"), r["n"], np.frombuffer(r["whole"], "f8"), r["moved"]


def assign_side(assign: DataFrame, planes: dict[str, tuple[np.ndarray, float]]) -> DataFrame:
    """``assign`` (id, deg, v, path) with ``side``: 1 where w . v > b in the plane of the row's set. Sets without a plane go."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                code = b.column(3).dictionary_encode()
                own, z = code.indices.to_numpy(), b.column(2).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1).astype("f8")
                side = np.full(b.num_rows, -1, "i4")
                for c, path in enumerate(code.dictionary.to_pylist()):
                    if path in planes:
                        w, shift = planes[path]
                        side[own == c] = z[own == c] @ w > shift
                there = pa.array(side >= 0)
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(side)], ["id", "deg", "v", "path", "side"]).filter(there)

    return assign.select("id", "deg", "v", "path").mapInArrow(run, "id long, deg long, v array<float>, path string, side int")


def lloyd_step(assign: DataFrame, centres: DataFrame, width: int) -> DataFrame:
    """One exact step for all sets at once: (path, side, n, centre, error) from ``centres`` (path, c0, c1).

    Sums are aggregated on the map side; what is shuffled has two rows for each set and task.
    """
    near = assign.join(F.broadcast(centres), "path")
    d0, d1 = (F.aggregate(F.zip_with("v", c, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x) for c in ("c0", "c1"))
    near = near.withColumn("d0", d0).withColumn("d1", d1).withColumn("side", (F.col("d1") < F.col("d0")).cast("int"))
    sums = [F.avg(F.element_at("v", k + 1).cast("double")).alias(f"_{k}") for k in range(width)]
    out = near.groupBy("path", "side").agg(F.count(F.lit(1)).alias("n"), F.sum(F.least("d0", "d1")).alias("error"), *sums)
    return out.select("path", "side", "n", F.array(*[f"_{k}" for k in range(width)]).alias("centre"), "error")


def k_means(z: DataFrame, k: int, seed: int = 0, max_iter: int = 20) -> DataFrame:
    """(id, block) of ``z`` (id, v) for a given number of blocks; block is the least id in it."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = z.select("id", array_to_vector(F.col("v").cast("array<double>")).alias("features"))
    out = KMeans(k=k, seed=seed, maxIter=max_iter).fit(rows).transform(rows).select("id", "prediction")
    least = out.groupBy("prediction").agg(F.min("id").alias("block"))
    return out.join(F.broadcast(least), "prediction").select("id", "block")
