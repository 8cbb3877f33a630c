"""Near copies by the similarity of their sets of word shingles, exactly.

Two texts are near copies if the sets of their five-word shingles have a Jaccard similarity of at least 4/5. Shingles
are put into one order, rare ones first; sets that similar share one of the first fifth (and one more) of either. So
only these are dealt out, and what meets under one is checked by whole sets: first what the Gray index over fingerprints
joins and each member against the one with the fewest rarer shingles, then, where members are still apart, each with
each. The order is from bounded counts, which bear on the speed alone.
"""

from __future__ import annotations

from collections.abc import Iterable
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_map, as_bytes, durable, join_uneven, written
from .components import components
from .simhash import SEED, fingerprints, least_of_each
from .simhash import links as index_links

WORDS = 5
PART, WHOLE = 4, 5  # near copies share at least so many parts of the whole
BUCKETS = 1 << 20  # counts that shingles are ordered by
CELL = 1 << 12  # buckets in a row of counts
MARKS = 16  # longs of 64 bits that bound from below in how many shingles two sets differ


def shingles(text: bytes, words: int = WORDS) -> np.ndarray:
    """The distinct hashes of a text's shingles, sorted; a shorter text is one shingle, one without words has none."""
    parts = text.lower().split()
    if not parts:
        return np.empty(0, "i8")
    joined = b" ".join(parts)
    n = len(parts) - words + 1
    if n <= 1:
        hashes = xxhash.xxh64_digest(joined, SEED)
    else:
        ends = np.cumsum(np.fromiter(map(len, parts), "i8", len(parts)) + 1) - 1
        starts = np.concatenate([[0], ends[:-1] + 1])
        hashes = b"".join([xxhash.xxh64_digest(joined[a:b], SEED) for a, b in zip(starts[:n].tolist(), ends[words - 1 :].tolist(), strict=True)])
    return np.unique(np.frombuffer(hashes, ">i8").astype("i8"))


def bucket(grams: np.ndarray) -> np.ndarray:
    return (grams.view(np.uint64) & np.uint64(BUCKETS - 1)).astype("i8")


def sets(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """``docs`` (key, text) with node; texts with equal sets have one node."""

    def rows(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            node = [xxhash.xxh64_intdigest(shingles(t, words).tobytes(), SEED) for t in as_bytes(batch.column(1)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.array(node, "u8").view("i8"))], ["key", "text", "node"])

    return arrow_map(docs, rows, f"key {docs.schema['key'].dataType.simpleString()}, text string, node long")


def counts(texts: DataFrame, words: int = WORDS) -> np.ndarray:
    """How many sets of ``texts`` (node, text) have a shingle in each bucket."""

    def rows(batches: Iterable[pa.RecordBatch]):
        found = np.zeros(BUCKETS, "i8")
        for batch in batches:
            for t in as_bytes(batch.column(1)).to_pylist():
                np.add.at(found, bucket(shingles(t, words)), 1)
        cells = found.reshape(-1, CELL)
        full = np.flatnonzero(cells.any(axis=1))
        if len(full):
            yield pa.RecordBatch.from_arrays([pa.array(full), pa.array([cells[k].astype("u4").tobytes() for k in full], pa.binary())], ["cell", "n"])

    def total(key, table):
        n = sum(np.frombuffer(x, "u4").astype("i8") for x in table["n"].to_pylist())
        return pa.table({"cell": [key[0].as_py()], "n": pa.array([n.tobytes()], pa.binary())})

    out = np.zeros((BUCKETS // CELL, CELL), "i8")
    for r in arrow_map(texts, rows, "cell long, n binary").groupBy("cell").applyInArrow(total, "cell long, n binary").collect():
        out[r["cell"]] = np.frombuffer(r["n"], "i8")
    return out.reshape(-1)


def firsts(texts: DataFrame, often: np.ndarray, words: int = WORDS) -> DataFrame:
    """(gram, node, n, at) of the shingles that come first in each set of ``texts`` (node, text), with their places."""
    often = texts.sparkSession.sparkContext.broadcast(often.astype("u4" if often.max(initial=0) < 1 << 32 else "u8"))

    def rows(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            held = []
            for node, t in zip(batch.column(0).to_pylist(), as_bytes(batch.column(1)).to_pylist(), strict=True):
                own = shingles(t, words)
                n = len(own)
                if n:
                    first = own[np.lexsort((own, often.value[bucket(own)]))][: n - -(-PART * n // WHOLE) + 1]
                    held.append((first, np.full(len(first), node), np.full(len(first), n), np.arange(len(first))))
            if held:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c).astype("i8")) for c in zip(*held, strict=True)], ["gram", "node", "n", "at"])

    return arrow_map(texts, rows, "gram long, node long, n long, at long")


def could_be(x: str, y: str) -> Column:
    """Whether two sets that meet can be near copies, by the sizes and places in columns with these endings.

    Of what is common, one comes first in both; what is from there on must be enough.
    """
    enough = F.floor((PART * (F.col(f"n{x}") + F.col(f"n{y}")) + PART + WHOLE - 1) / (PART + WHOLE))
    return (F.col(f"n{x}") - F.col(f"at{x}") >= enough) & (F.col(f"n{y}") - F.col(f"at{y}") >= enough)


def similar(pairs: DataFrame, texts: DataFrame, words: int = WORDS) -> DataFrame:
    """Those of ``pairs`` (a, b) of nodes of ``texts`` (node, text) that are near copies."""
    pairs = written(pairs)
    ends = written(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct())
    own = texts.join(ends, "node")
    met = pairs.join(own.withColumnsRenamed({"node": "a", "text": "x"}), "a").join(own.withColumnsRenamed({"node": "b", "text": "y"}), "b").select("a", "b", "x", "y")

    def check(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            near = []
            for x, y in zip(*[as_bytes(c).to_pylist() for c in batch.columns[2:]], strict=True):
                x, y = shingles(x, words), shingles(y, words)
                common = len(np.intersect1d(x, y, assume_unique=True))
                near.append(WHOLE * common >= PART * (len(x) + len(y) - common))
            yield pa.RecordBatch.from_arrays(batch.columns[:2], ["a", "b"]).filter(pa.array(near, pa.bool_()))

    return durable(arrow_map(met, check, "a long, b long"))


def indexed(texts: DataFrame, words: int = WORDS) -> DataFrame:
    """Pairs (a, b) of nodes of ``texts`` (node, text) that the Gray index over their fingerprints joins, few and unchecked."""
    prints = written(fingerprints(texts.select("node", "text"), "text", "fp", words))
    homes = written(prints.groupBy("fp").agg(F.min("node").alias("home"), F.count(F.lit(1)).alias("n")))
    same = join_uneven(prints, homes, "fp", "n", prints.count()).where("node <> home").select(F.col("home").alias("a"), F.col("node").alias("b"))
    one, two = homes.select(F.col("fp").alias("a"), F.col("home").alias("x")), homes.select(F.col("fp").alias("b"), F.col("home").alias("y"))
    return same.unionByName(index_links(homes.select("fp")).join(one, "a").join(two, "b").select(F.col("x").alias("a"), F.col("y").alias("b")))


def marks(texts: DataFrame, words: int = WORDS) -> DataFrame:
    """(node, marks) of ``texts`` (node, text): a bit is 1 if an odd number of shingles fall on it.

    Sets differ in at least as many shingles as their marks do in bits.
    """

    def rows(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            bits = [np.bincount((shingles(t, words).view(np.uint64) >> np.uint64(32)).astype("i8") % (64 * MARKS), minlength=64 * MARKS) & 1 for t in as_bytes(batch.column(1)).to_pylist()]
            longs = np.packbits(np.array(bits, "u1").reshape(-1, 64 * MARKS), axis=1).view("i8")
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(longs), pa.list_(pa.int64()))], ["node", "marks"])

    return arrow_map(texts.select("node", "text"), rows, "node long, marks array<long>")


def few_differ(x: str, y: str) -> Column:
    """Whether sets with these endings can be near copies by their marks: what is not common is in one of them alone."""
    enough = F.floor((PART * (F.col(f"n{x}") + F.col(f"n{y}")) + PART + WHOLE - 1) / (PART + WHOLE))
    bits = [F.bit_count(F.col(f"marks{x}")[k].bitwiseXOR(F.col(f"marks{y}")[k])) for k in range(MARKS)]
    return reduce(Column.__add__, bits) <= F.col(f"n{x}") + F.col(f"n{y}") - 2 * enough


def in_order(x: str, y: str) -> list[Column]:
    return [F.least(x, y).alias("a"), F.greatest(x, y).alias("b")]


def near_links(texts: DataFrame, words: int = WORDS) -> DataFrame:
    """Links (a, b) that connect all near copies of ``texts`` (node, text; a node once), directly or over others."""
    by = Window.partitionBy("gram")
    met = firsts(texts, counts(texts, words), words).withColumn("met", F.count(F.lit(1)).over(by)).where("met > 1")
    # Sets of about a size meet the one with the fewest rarer shingles, which is likest to all; ranges of sizes overlap.
    size = F.log("n") / np.log(WHOLE / PART)
    mid = F.min(F.struct("at", "node", "n"))
    met = written(met.withColumn("mids", F.array(*[mid.over(Window.partitionBy("gram", F.floor(size + k))) for k in (0, 0.5)])).drop("met"))
    star = met.select(F.explode("mids").alias("mid"), F.col("node").alias("node_y"), F.col("n").alias("n_y"), F.col("at").alias("at_y"))
    star = star.select(F.col("mid.node").alias("node_x"), F.col("mid.n").alias("n_x"), F.col("mid.at").alias("at_x"), "node_y", "n_y", "at_y")
    star = star.where((F.col("node_x") != F.col("node_y")) & could_be("_x", "_y")).select(*in_order("node_x", "node_y"))
    links = similar(star.unionByName(indexed(texts, words).select(*in_order("a", "b"))).distinct(), texts, words)
    roots = components(links).withColumnRenamed("root", "__root")
    apart = met.drop("mids").join(roots, "node", "left").withColumn("root", F.coalesce("__root", "node")).drop("__root")
    apart = written(apart.withColumn("low", F.min("root").over(by)).withColumn("high", F.max("root").over(by)).where("low < high").drop("low", "high"))
    marked = apart.join(marks(texts.join(apart.select("node").distinct(), "node", "left_semi"), words), "node")
    x, y = (marked.select("gram", *[F.col(c).alias(f"{c}_{s}") for c in ("node", "n", "at", "root", "marks")]) for s in "xy")
    rest = x.join(y, "gram").where((F.col("node_x") < F.col("node_y")) & (F.col("root_x") != F.col("root_y")) & could_be("_x", "_y") & few_differ("_x", "_y"))
    return links.unionByName(similar(rest.select(F.col("node_x").alias("a"), F.col("node_y").alias("b")).distinct(), texts, words))


def near_copies(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc_id, component_id) of the rows of ``docs`` (doc_id, text): the least id reachable over near copies.

    Null keys are never the least one unless there is no other. Repeated rows stay; texts without words are linked.
    """
    whole = sets(docs.select(F.col("doc_id").alias("key"), "text"), words)
    found = durable(whole.select("key", "node"))
    own = found.groupBy("node", "key").agg(F.count(F.lit(1)).alias("n"))
    nodes = written(own.groupBy("node").agg(F.min_by(F.struct("key", "n"), F.struct(F.col("key").isNull(), "key")).alias("one")).select("node", "one.key", "one.n"))
    one = nodes.alias("o")
    texts = whole.alias("w").join(one, (F.col("w.node") == F.col("o.node")) & F.col("w.key").eqNullSafe(F.col("o.key"))).select("w.node", "w.text", "o.n")
    kept = texts.where("n = 1")
    if not nodes.where("n > 1").isEmpty():
        kept = kept.unionByName(texts.where("n > 1").dropDuplicates(["node"]))
    roots = components(near_links(written(kept.drop("n")), words))
    sizes = own.groupBy("node").agg(F.sum("n").alias("rows"))
    rooted = durable(nodes.join(roots, "node", "left").join(sizes, "node").select("node", "key", "rows", F.coalesce("root", "node").alias("root")))
    least = written(rooted.groupBy("root").agg(F.min("key").alias("component_id"), F.count(F.lit(1)).alias("n")))
    classes = written(join_uneven(rooted, least, "root", "n", rooted.count()).select("node", "rows", "component_id"))
    return join_uneven(found, classes, "node", "rows", found.count()).select(F.col("key").alias("doc_id"), "component_id")


def one_of_each(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """The rows of ``docs`` (doc_id, text and more) with the least id of each group of near copies, with its columns."""
    return least_of_each(docs, near_copies(docs, words))
