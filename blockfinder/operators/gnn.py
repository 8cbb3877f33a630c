"""Random embeddings: one forward pass of an untrained graph convolution stack."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.rng import gauss_block, uniform_block
from ..plans.state import dropped, fresh_folder, part_files, placed, plainly_shared, settle, swept, written
from .graph import Graph
from .kernels import IDS_AT_ONCE, arcs_at_once, by_source, hub_salt, matrix, summed_by, vectors

#: Vectors of all nodes up to this size go to each task; larger ones are cut into blocks of the other size.
BROADCAST_BYTES = 256 << 20
BLOCK_BYTES = 96 << 20
PART_BYTES = 32 << 20  # vectors of a part of the nodes in the plan ``files``; a task holds two parts
PARALLEL_BLOCKS = 4  # with fewer blocks, sources are cut finer, to keep all cores busy
ACTIVATIONS: dict[str, Callable[[np.ndarray], np.ndarray]] = {"tanh": np.tanh, "relu": lambda x: np.maximum(x, 0), "identity": lambda x: x}


def weights(rows: int, columns: int, seed: int, layer: int, init: str = "orthogonal") -> np.ndarray:
    """The random weights of a layer.

    ``gaussian`` is the law of the feature projection; ``orthogonal`` makes its shorter side's vectors orthonormal, so
    that a layer as wide as the one before keeps all distances, however many there are.
    """
    ids = np.arange(rows)
    if init == "gaussian":
        return gauss_block(seed * 1009 + layer + 1, ids, columns).astype("f8") * columns**-0.5
    if init == "glorot_uniform":
        return (2 * uniform_block(seed * 1009 + layer + 1, ids, columns) - 1) * np.sqrt(6 / (rows + columns))
    if init == "orthogonal":
        long, short = max(rows, columns), min(rows, columns)
        q, r = np.linalg.qr(gauss_block(seed * 1009 + layer + 1, np.arange(long), short).astype("f8"))
        q = q * np.where(np.diag(r) < 0, -1.0, 1.0)
        return q if rows >= columns else q.T
    raise ValueError("init must be orthogonal, gaussian or glorot_uniform")


def unit_rows(x: np.ndarray) -> np.ndarray:
    size = np.linalg.norm(x, axis=1, keepdims=True)
    return x / np.where(size > 0, size, 1)


def dealt_arcs(g: Graph, loops: bool = True) -> DataFrame:
    """(src, dst, deg): arcs and, with ``loops``, one from each node to itself; a node's arcs are side by side."""
    arcs = g.arcs.select("src", "dst", F.col("dsrc").alias("deg"))
    if loops:
        arcs = arcs.unionByName(g.nodes.select(F.col("id").alias("src"), F.col("id").alias("dst"), "deg"))
    return settle(by_source(arcs, ["dst", "deg"], hub_salt(g)))


def plan_for(n: int, width: int, mean_degree: float) -> str:
    """``broadcast`` while all vectors are small, ``blocks`` while there are fewer blocks of them than a node has arcs, else ``join``.

    In a whole pass, ``files`` stands for ``blocks`` where Python can open the shared folder and no node's arcs are dealt out.
    """
    size = 4 * n * width
    return "broadcast" if size <= BROADCAST_BYTES else "blocks" if size <= BLOCK_BYTES * max(2.0, mean_degree / 2) else "join"


Finish = Callable[[np.ndarray, np.ndarray], np.ndarray]


def propagate(arcs: DataFrame, z: DataFrame, width: int, n: int, how: str, finish: Finish, whole: bool = True) -> DataFrame:
    """(id, deg, v): ``finish(deg, sums)`` of the sums of ``z`` (id, v) over the ends of each node's ``arcs`` (src, dst, deg).

    ``broadcast``: all of z goes to each task. ``blocks``: z is cut into blocks; a block meets the arcs that lead into it,
    by blocks of their sources, and what is moved are blocks and their partial sums, not a vector for each arc.
    ``join``: a vector for each arc, added up where it is made and once more by node. ``whole``: no node's arcs are in
    several partitions of ``arcs``.
    """
    schema = "id long, deg long, v array<float>"

    def done(parts: Iterable[tuple[np.ndarray, np.ndarray, np.ndarray]], finish: Finish):
        for ids, deg, sums in summed_by(parts):
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(deg), vectors(finish(deg, sums))], ["id", "deg", "v"])

    step = arcs_at_once(width)
    as_is: Finish = lambda deg, sums: sums
    if how == "broadcast":
        table = z.select("id", "v").toArrow()
        ids = table["id"].to_numpy()
        order = np.argsort(ids)
        shared = z.sparkSession.sparkContext.broadcast((ids[order], matrix(table["v"].combine_chunks(), width)[order]))

        def look_up(batches):
            ids, rows = shared.value
            for batch in batches:
                src, dst, deg = (c.to_numpy() for c in batch.columns)
                for k in range(0, len(src), step):
                    part = slice(k, k + step)
                    yield src[part], deg[part], rows[np.searchsorted(ids, dst[part])]

        summed = arcs.mapInArrow(lambda batches: done(look_up(batches), finish if whole else as_is), schema)
        if whole:
            return summed
    elif how == "blocks":
        count = max(2, -(-4 * n * width // BLOCK_BYTES))
        wide = max(count, -(-2 * z.sparkSession.sparkContext.defaultParallelism // count)) if count < PARALLEL_BLOCKS else count
        block = lambda c, of: F.pmod(F.xxhash64(c), F.lit(of)).cast("int")
        cells = arcs.select(block("src", wide).alias("i"), block("dst", count).alias("j"), "src", "dst", "deg").groupBy("i", "j")
        sent = z.select(F.explode(F.sequence(F.lit(0), F.lit(wide - 1))).alias("i"), block("id", count).alias("j"), "id", "v").groupBy("i", "j")

        def meet(left, right):
            if not left.num_rows or not right.num_rows:
                return pa.table({"id": pa.array([], pa.int64()), "deg": pa.array([], pa.int64()), "v": pa.array([], pa.list_(pa.float32()))})
            ids = right["id"].to_numpy()
            order = np.argsort(ids)
            rows, ids = matrix(right["v"].combine_chunks(), width), ids[order]
            by_src = np.argsort(left["src"].to_numpy(), kind="stable")
            src, deg = left["src"].to_numpy()[by_src], left["deg"].to_numpy()[by_src]
            place = order[np.searchsorted(ids, left["dst"].to_numpy()[by_src])]
            parts = ((src[k : k + step], deg[k : k + step], rows[place[k : k + step]]) for k in range(0, len(src), step))
            return pa.Table.from_batches(list(done(parts, as_is)))

        summed = cells.cogroup(sent).applyInArrow(meet, schema)
    else:
        sent = arcs.join(z.select(F.col("id").alias("dst"), "v"), "dst").select("src", "deg", "v").sortWithinPartitions("src")
        summed = sent.mapInArrow(lambda batches: done(columns_of(batches, width), as_is), schema)
    return summed.repartition("id").sortWithinPartitions("id").mapInArrow(lambda batches: done(columns_of(batches, width), finish), schema)


def columns_of(batches: Iterable[pa.RecordBatch], width: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    return ((b.column(0).to_numpy(), b.column(1).to_numpy(), matrix(b.column(2), width)) for b in batches if b.num_rows)


@dataclass(frozen=True)
class Parts:
    """Arcs in files of the shared folder: ``p=k`` holds those from part k of the nodes, ordered by the part of their end and by source.

    Vectors lie in the same parts (id, deg, v as bytes), ordered by id. A layer is one task for each part of the sources: it
    adds up what its arcs lead to, part by part, straight from the files. Nothing is shuffled, and what is on disk are
    the arcs once and the vectors before and after the layer.
    """

    folder: str
    count: int

    @staticmethod
    def of(g: Graph, width: int, loops: bool = True) -> Parts:
        count = max(g.nodes.sparkSession.sparkContext.defaultParallelism, -(-4 * g.n * width // PART_BYTES))
        arcs = g.arcs.select("src", "dst")
        if loops:
            arcs = arcs.unionByName(g.nodes.select(F.col("id").alias("src"), F.col("id").alias("dst")))
        folder = fresh_folder(g.nodes.sparkSession)
        dealt = arcs.select(part_of("src", count).alias("p"), part_of("dst", count).alias("q"), "src", "dst").repartitionById(count, F.col("p"))
        dealt.sortWithinPartitions("p", "q", "src").write.option("compression", "zstd").partitionBy("p").parquet(folder)
        return Parts(folder, count)

    def put(self, z: DataFrame, width: int) -> str:
        """The folder of ``z`` (id, deg, v) in parts."""
        dealt = z.select("id", "deg", "v", part_of("id", self.count).alias("p")).repartitionById(self.count, F.col("p")).sortWithinPartitions("p", "id")
        return self.write(dealt.mapInArrow(lambda batches: (as_bytes(b.column(0), b.column(1), matrix(b.column(2), width), b.column(3)) for b in batches if b.num_rows), BYTES))

    def write(self, z: DataFrame) -> str:
        folder = fresh_folder(z.sparkSession)
        z.write.option("compression", "none").option("parquet.enable.dictionary", "false").partitionBy("p").parquet(folder)
        return folder

    def summed(self, spark, folder: str, width: int, finish: Finish, packed: bool) -> DataFrame:
        """``finish(deg, sums)`` of all nodes with arcs, of the vectors in ``folder``: (id, deg, v), ``packed`` as bytes with their part."""
        arcs, step = self.folder, arcs_at_once(width)

        def part(k: int):
            ids, deg, _ = read_part(folder, k, None)
            sums, seen = np.zeros((len(ids), width)), np.zeros(len(ids), bool)
            at, ends, rows = -1, None, None
            for file in part_files(arcs, "p", k):
                for batch in pq.ParquetFile(file).iter_batches(1 << 17, columns=["q", "src", "dst"]):
                    q, src, dst = (c.to_numpy() for c in batch.columns)
                    bounds = np.flatnonzero(np.r_[True, q[1:] != q[:-1], True])
                    for first, last in zip(bounds[:-1], bounds[1:], strict=True):
                        if q[first] != at:
                            rows = None  # one part at a time
                            at = int(q[first])
                            ends, _, rows = read_part(folder, at, width)
                        own, place = np.searchsorted(ids, src[first:last]), np.searchsorted(ends, dst[first:last])
                        for a in range(0, len(own), step):
                            piece = own[a : a + step]
                            starts = np.flatnonzero(np.r_[True, piece[1:] != piece[:-1]])
                            sums[piece[starts]] += np.add.reduceat(rows[place[a : a + step]], starts, axis=0)
                            seen[piece[starts]] = True
            rows = None
            there = np.flatnonzero(seen)
            for a in range(0, len(there), IDS_AT_ONCE):
                some = there[a : a + IDS_AT_ONCE]
                out = finish(deg[some], sums[some])
                if packed:
                    yield as_bytes(pa.array(ids[some]), pa.array(deg[some]), out, pa.array(np.full(len(some), k, "i4")))
                else:
                    yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(deg[some]), vectors(out)], ["id", "deg", "v"])

        def run(batches):
            for batch in batches:
                for k in batch.column(0).to_pylist():
                    yield from part(k)

        return spark.range(0, self.count, 1, self.count).mapInArrow(run, BYTES if packed else "id long, deg long, v array<float>")


BYTES = "id long, deg long, v binary, p int"


def part_of(node: str, count: int) -> Column:
    return F.pmod(F.xxhash64(F.col(node).cast("long")), F.lit(count)).cast("int")


def as_bytes(ids: pa.Array, deg: pa.Array, rows: np.ndarray, part: pa.Array) -> pa.RecordBatch:
    rows = np.ascontiguousarray(rows, "f4")
    offsets = np.arange(len(rows) + 1, dtype="i4") * (4 * rows.shape[1])
    return pa.RecordBatch.from_arrays([ids, deg, pa.BinaryArray.from_buffers(pa.binary(), len(rows), [None, pa.py_buffer(offsets), pa.py_buffer(rows)]), part], ["id", "deg", "v", "p"])


def read_part(folder: str, k: int, width: int | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """ids, degrees and, with a ``width``, vectors of a part, by id."""
    ids, deg, rows = [np.zeros(0, "i8")], [np.zeros(0, "i8")], [np.zeros((0, width or 0), "f4")]
    files = part_files(folder, "p", k)
    for file in files:
        table = pq.ParquetFile(file).read(columns=["id", "deg"] if width is None else ["id", "deg", "v"])
        ids.append(table["id"].to_numpy())
        deg.append(table["deg"].to_numpy())
        for piece in table["v"].chunks if width is not None else []:
            first = np.frombuffer(piece.buffers()[1], "i4")[piece.offset] if len(piece) else 0
            rows.append(np.frombuffer(piece.buffers()[2] or b"", "f4", len(piece) * width, first).reshape(-1, width))
    ids, deg, rows = np.concatenate(ids), np.concatenate(deg), np.concatenate(rows)
    if len(files) > 1:
        order = np.argsort(ids)
        ids, deg, rows = ids[order], deg[order], rows[order] if width is not None else rows
    return ids, deg, rows


def neighbour_sums(g: Graph, z: DataFrame, width: int, how: str = "auto", arcs: DataFrame | None = None) -> DataFrame:
    """(id, v): the sum of the neighbours' rows of ``z`` (id, v). ``arcs``: those of ``dealt_arcs`` without loops, to be used again."""
    how = plan_for(g.n, width, 2 * g.m / max(1, g.n)) if how == "auto" else how
    arcs = dealt_arcs(g, loops=False) if arcs is None else arcs
    return propagate(arcs, z, width, g.n, how, lambda deg, sums: sums, hub_salt(g) == 1).select("id", "v")


def ready(z: DataFrame, w: np.ndarray | None) -> DataFrame:
    """``z`` (id, deg, v): rows times ``w`` (None: as they are), over the root of degree + 1."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                rows = matrix(b.column(2), -1 if w is None else w.shape[0]).astype("f8")
                rows = (rows if w is None else rows @ w) / np.sqrt(b.column(1).to_numpy() + 1.0)[:, None]
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), vectors(rows)], ["id", "deg", "v"])

    return z.select("id", "deg", "v").mapInArrow(run, "id long, deg long, v array<float>")


def after_sum(act: str, normalise: bool, following: np.ndarray | None = None) -> Finish:
    """A layer from its sums on, and, where there is a next one, its rows times that one's weights."""
    activate = ACTIVATIONS[act]

    def finish(deg: np.ndarray, sums: np.ndarray) -> np.ndarray:
        root = np.sqrt(deg + 1.0)[:, None]
        rows = activate(sums / root)
        rows = unit_rows(rows) if normalise else rows
        return rows if following is None else rows @ following / root

    return finish


def layer(g: Graph, z: DataFrame, w: np.ndarray | None, width: int, act: str = "tanh", normalise: bool = True, how: str = "auto") -> DataFrame:
    """One layer over ``z`` (id, deg, v): neighbours and self, each over the root of degree + 1, times ``w``, activated.

    The weights are applied before the sum, where rows are wide, so that what is moved is of the new width.
    ``w`` None: no multiplication.
    """
    how = plan_for(g.n, width, 2 * g.m / max(1, g.n)) if how == "auto" else how
    return propagate(dealt_arcs(g), written(ready(z, w)), width, g.n, how, after_sum(act, normalise), hub_salt(g) == 1)


def normalise(z: DataFrame) -> DataFrame:
    """Rows of length 1; zero rows stay."""

    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), vectors(unit_rows(matrix(b.column(2), -1).astype("f8")))], ["id", "deg", "v"])

    return z.select("id", "deg", "v").mapInArrow(run, "id long, deg long, v array<float>")


def forward(g: Graph, y: DataFrame, layers: tuple[int, ...], seed: int = 0, act: str = "tanh", init: str = "orthogonal", normalise: bool = True, first_weights: bool = True, how: str = "auto") -> DataFrame:
    """(id, deg, v) after one pass of ``y`` (id, v) through layers of the given sizes; ``layers[0]`` is y's width.

    Without ``first_weights``, the first layer's weights are taken to be in ``y`` already (its width is ``layers[1]``).
    Each layer is one pass over arcs that are dealt out once; it ends with the next one's weights, and is written.
    """
    z = g.nodes.join(y.select("id", "v"), "id").select("id", "deg", "v")
    depth = len(layers) - 1
    if depth < 1:
        return z
    whole, plan = hub_salt(g) == 1, lambda width: plan_for(g.n, width, 2 * g.m / max(1, g.n)) if how == "auto" else how
    w = [None if k == 0 and not first_weights else weights(layers[k], layers[k + 1], seed, k, init) for k in range(depth)]
    if how == "files" or (how == "auto" and whole and plan(max(layers[1:])) == "blocks" and plainly_shared(z.sparkSession)):
        return through_files(g, ready(z, w[0]), layers[1:], [after_sum(act, normalise, x) for x in [*w[1:], None]])
    arcs, (z, folder) = dealt_arcs(g), placed(ready(z, w[0]))
    for k in range(depth):
        width, before = layers[k + 1], folder
        z, folder = placed(propagate(arcs, z, width, g.n, plan(width), after_sum(act, normalise, w[k + 1] if k + 1 < depth else None), whole))
        dropped(z.sparkSession, before)
    return z


def through_files(g: Graph, z: DataFrame, widths: tuple[int, ...], finish: list[Finish]) -> DataFrame:
    """(id, deg, v) after a layer of each width, by ``Parts``. Vectors that the next layer has read are deleted."""
    spark = z.sparkSession
    parts = Parts.of(g, max(widths))
    own = parts.put(z, widths[0])
    swept(spark)
    for k, width in enumerate(widths[:-1]):
        # A layer's rows come out times the next one's weights, so they have its width.
        before, own = own, parts.write(parts.summed(spark, own, width, finish[k], packed=True))
        dropped(spark, before)
    z = written(parts.summed(spark, own, widths[-1], finish[-1], packed=False))
    dropped(spark, own, parts.folder)
    return z


def layer_long(g: Graph, z: DataFrame, columns: int, rows: int, seed: int, act: str = "tanh") -> DataFrame:
    """One layer in DataFrame functions alone, over ``z`` (id, dim, val), with weights that SQL engines share: (id, dim, val)."""
    from ..functions.rng import gauss

    own = z.join(g.nodes, "id").select("id", "dim", (F.col("val") / F.sqrt(F.col("deg") + 1.0)).alias("val"))
    sent = g.arcs.select("src", "dst").join(own.withColumnRenamed("id", "dst"), "dst").select(F.col("src").alias("id"), "dim", "val").unionByName(own)
    agg = sent.groupBy("id", "dim").agg(F.sum("val").alias("val"))
    out = agg.select("id", F.col("dim").alias("row"), "val", F.explode(F.sequence(F.lit(0), F.lit(columns - 1))).alias("dim"))
    total = out.groupBy("id", "dim").agg(F.sum(F.col("val") * gauss(seed, F.col("row"), F.col("dim")) * columns**-0.5).alias("val")).join(g.nodes, "id")
    value = F.col("val") / F.sqrt(F.col("deg") + 1.0)
    done = {"tanh": F.tanh(value), "relu": F.greatest(value, F.lit(0.0)), "identity": value}[act]
    return total.select("id", "dim", done.alias("val"))


def normalise_long(z: DataFrame) -> DataFrame:
    size = z.groupBy("id").agg(F.sqrt(F.sum(F.col("val") * F.col("val"))).alias("size"))
    return z.join(size, "id").select("id", "dim", F.when(F.col("size") > 0, F.col("val") / F.col("size")).otherwise(0.0).alias("val"))
