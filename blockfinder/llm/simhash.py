"""Near copies by SimHash, found through a hierarchical index in Gray order.

Fingerprints that differ in at most ``RADIUS`` bits agree in all bits of some choice of blocks, so each is sent to one
group for each choice, under the bits that it has there. A group's fingerprints are sorted by Gray rank, where
neighbours differ in few bits; nodes over runs of neighbours hold the bits that all of them share. Two nodes whose
shared bits differ in more than ``RADIUS`` places can't hold a link and go with all that is below them; differences
are counted anew, with more bits shared, on each level down. The result is exact.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, as_bytes, documents, durable, free_name, join_uneven, written
from .components import components

WORDS = 4
RADIUS = 4
SEED = 42
FAN = 8  # children of a node
CHUNK = 8192  # most fingerprints of a group that meet in one piece of work
AT_ONCE = 65_536
PAIRS_AT_ONCE = 1 << 20
SALT = 32
#: Distinct fingerprints up to which so many blocks are enough to keep chance groups small.
BLOCKS = ((1 << 21, RADIUS + 1), (1 << 29, RADIUS + 2), (1 << 35, RADIUS + 3), (1 << 62, RADIUS + 4))


def fingerprint(text: bytes, words: int = WORDS) -> bytes:
    """Eight bytes. A bit is 1 if it is set in over half of the shingles' hashes; without a word, all are 0."""
    parts = text.lower().split()
    if not parts:
        return bytes(8)
    joined = b" ".join(parts)
    n = max(1, len(parts) - words + 1)
    if n == 1:
        hashes = xxhash.xxh64_digest(joined, SEED)
    else:
        ends = np.cumsum(np.fromiter(map(len, parts), "i8", len(parts)) + 1) - 1
        starts = np.concatenate([[0], ends[:-1] + 1])
        hashes = b"".join([xxhash.xxh64_digest(joined[a:b], SEED) for a, b in zip(starts[:n].tolist(), ends[words - 1 :].tolist(), strict=True)])
    bits = np.unpackbits(np.frombuffer(hashes, np.uint8).reshape(n, 8), axis=1)
    return np.packbits(2 * bits.sum(axis=0, dtype="i8") > n).tobytes()


def fingerprints(df: DataFrame, text: str = "text", out: str = "fp", words: int = WORDS) -> DataFrame:
    """All rows and columns of ``df`` but the text, with its fingerprint as a (signed) long; null counts as empty.

    A column with the name of the new one gives way to it.
    """
    at = df.columns.index(text)
    kept = [c for c in df.columns if c not in (text, out)]
    places = [df.columns.index(c) for c in kept]

    def rows(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            found = b"".join([fingerprint(t, words) for t in as_bytes(batch.column(at)).to_pylist()])
            columns = [batch.column(k) for k in places]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(np.frombuffer(found, ">i8").astype("i8"))], [*kept, out])

    return arrow_map(df, rows, ", ".join([*[f"`{c}` {df.schema[c].dataType.simpleString()}" for c in kept], f"`{out}` long"]))


def gray_rank(fp: np.ndarray) -> np.ndarray:
    """The place of each bit pattern in the reflected Gray order."""
    rank = fp.copy()
    for step in (1, 2, 4, 8, 16, 32):
        rank ^= rank >> np.uint64(step)
    return rank


class GrayIndex:
    """An index over runs of fingerprints, sorted by (run, Gray rank). Level 0 are the fingerprints."""

    def __init__(self, run: np.ndarray, fp: np.ndarray):
        self.every, self.some, self.first, self.count = [fp], [fp], [], []
        while True:
            starts = np.flatnonzero(np.r_[True, run[1:] != run[:-1]])
            sizes = np.diff(np.r_[starts, len(run)])
            if self.first and len(starts) == len(run):
                return
            parts = -(-sizes // FAN)
            first = np.repeat(starts, parts) + FAN * (np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts))
            self.first.append(first)
            self.count.append(np.diff(np.r_[first, len(run)]).clip(max=FAN))
            self.count[-1] = np.minimum(self.count[-1], np.repeat(starts + sizes, parts) - first)
            self.every.append(np.bitwise_and.reduceat(self.every[-1], first))
            self.some.append(np.bitwise_or.reduceat(self.some[-1], first))
            run = run[first]

    def links(self, left: np.ndarray, right: np.ndarray, radius: int):
        """Pairs of fingerprints within ``radius``, from pairs of top nodes; a node with itself gives each pair once."""
        work = [(len(self.first), left, right)]
        while work:
            level, a, b = work.pop()
            if len(a) > PAIRS_AT_ONCE // (FAN * FAN) and level:
                cut = PAIRS_AT_ONCE // (FAN * FAN)
                work.append((level, a[cut:], b[cut:]))
                a, b = a[:cut], b[:cut]
            if not level:
                yield a, b
                continue
            na, nb = self.count[level - 1][a], self.count[level - 1][b]
            each = na * nb
            place = np.arange(each.sum()) - np.repeat(np.cumsum(each) - each, each)
            wide = np.repeat(nb, each)
            x, y = np.repeat(self.first[level - 1][a], each) + place // wide, np.repeat(self.first[level - 1][b], each) + place % wide
            twin = np.repeat(a == b, each)
            fits = ~twin | ((x <= y) if level > 1 else (x < y))
            x, y = x[fits], y[fits]
            every, some = self.every[level - 1], self.some[level - 1]
            shared = ~((every[x] ^ some[x]) | (every[y] ^ some[y]))
            near = np.bitwise_count(shared & (every[x] ^ every[y])) <= radius
            if near.any():
                work.append((level - 1, x[near], y[near]))


def join_labels(labels: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Labels (each the place of a least member) after the components of a and b have been joined."""
    while True:
        x, y = labels[a], labels[b]
        apart = x != y
        if not apart.any():
            return labels
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(labels, np.maximum(x, y), np.minimum(x, y))
        while True:
            further = labels[labels]
            if (further == labels).all():
                break
            labels = further


def local_links(group: np.ndarray, side: np.ndarray, fp: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links that connect what is within ``radius`` in each group, as few as that takes.

    Where a group has two sides, only pairs of the one with the other are looked at.
    """
    order = np.lexsort((gray_rank(fp), side, group))
    group, side, fp = group[order], side[order], fp[order]
    run = np.cumsum(np.r_[True, (group[1:] != group[:-1]) | (side[1:] != side[:-1])]) - 1
    heads = np.flatnonzero(np.r_[True, run[1:] != run[:-1]])
    index = GrayIndex(run, fp)
    of = group[heads]
    paired = np.r_[of[1:] == of[:-1], False]
    alone = ~(paired | np.r_[False, paired[:-1]])
    left = np.flatnonzero(paired | alone)
    right = np.where(paired[left], left + 1, left)
    labels = np.arange(len(fp))
    for a, b in index.links(left, right, radius):
        labels = join_labels(labels, a, b)
    moved = np.flatnonzero(labels != np.arange(len(fp)))
    return fp[moved], fp[labels[moved]]


def block_masks(distinct: int, radius: int = RADIUS) -> list[int]:
    """For each choice of all but ``radius`` blocks, the bits of the chosen blocks."""
    blocks = next(n for most, n in BLOCKS if distinct <= most)
    edges = [64 * k // blocks for k in range(blocks + 1)]
    bits = [sum(1 << p for p in range(a, b)) for a, b in itertools.pairwise(edges)]
    return [sum(c) for c in itertools.combinations(bits, blocks - radius)]


def signed(value: int) -> int:
    return value - (1 << 64) if value >= 1 << 63 else value


def links(fps: DataFrame, radius: int = RADIUS, column: str = "fp") -> DataFrame:
    """Links (a, b) between distinct fingerprints that connect whatever is within ``radius``, over all of ``fps``.

    Groups over ``CHUNK`` are cut into chunks by a hash, and each pair of chunks is a piece of work of its own, so that
    no task holds a whole group.
    """
    masks = block_masks(fps.count(), radius)
    choices = F.array(*[F.struct(F.lit(k).alias("choice"), F.col(column).bitwiseAND(F.lit(signed(m))).alias("bits")) for k, m in enumerate(masks)])
    sent = fps.select(F.col(column).alias("fp"), F.explode(choices).alias("c")).select("fp", "c.choice", "c.bits")
    large = sent.groupBy("choice", "bits").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > 1)
    sent = sent.join(large, ["choice", "bits"])
    chunks = F.ceil(F.col("n") / CHUNK).cast("int")
    own = F.pmod(F.xxhash64("fp"), chunks.cast("long")).cast("int")
    sent = sent.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), chunks - 1)))
    sent = sent.select("choice", "bits", F.least("own", "other").alias("low"), F.greatest("own", "other").alias("high"), "own", "fp")
    key = ["choice", "bits", "low", "high"]
    dealt = sent.repartition(*key).sortWithinPartitions(*key)

    def rows(batches: Iterable[pa.RecordBatch]):
        held: list[np.ndarray] = []

        def work(part: np.ndarray):
            group = np.cumsum(np.r_[True, (part[1:, :4] != part[:-1, :4]).any(axis=1)])
            a, b = local_links(group, part[:, 4], part[:, 5].view(np.uint64), radius)
            return pa.RecordBatch.from_arrays([pa.array(a.view("i8")), pa.array(b.view("i8"))], ["a", "b"])

        for batch in batches:
            held.append(np.stack([c.to_numpy().astype("i8") for c in batch.columns], axis=1))
            if sum(map(len, held)) >= AT_ONCE:
                part = np.concatenate(held)
                last = np.flatnonzero((part[1:, :4] != part[:-1, :4]).any(axis=1))
                cut = last[-1] + 1 if len(last) else 0
                if cut:
                    yield work(part[:cut])
                held = [part[cut:]]
        if held and sum(map(len, held)):
            yield work(np.concatenate(held))

    return arrow_map(dealt, rows, "a long, b long")


def near_copies(df: DataFrame, key: str = "doc_id", text: str = "text", words: int = WORDS, radius: int = RADIUS) -> DataFrame:
    """Each row's fingerprint and the least key that is reachable over links: (key, fp, component_id).

    Texts without words have fingerprint zero and are linked like any other. Null keys are never the least one unless
    there is no other. Repeated rows stay; empty input gives no rows.
    """
    docs = durable(fingerprints(df.select(F.col(key).alias("__key"), F.col(text).alias("__text")), "__text", "fp", words))
    distinct = durable(docs.groupBy("fp").agg(F.min("__key").alias("__least"), F.count(F.lit(1)).alias("__rows")))
    roots = components(links(distinct.select("fp"), radius)).withColumnRenamed("node", "fp")
    rooted = durable(distinct.join(roots, "fp", "left").select("fp", "__least", "__rows", "root"))
    # Only fingerprints with a link meet their component's least key; a component of many is dealt over ``SALT`` parts.
    linked = rooted.where("root is not null").withColumn("__part", F.pmod(F.xxhash64("fp"), F.lit(SALT)))
    least = linked.groupBy("root").agg(F.min("__least").alias("component_id")).withColumn("__part", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALT - 1).cast("long"))))
    alone = rooted.where("root is null").select("fp", "__rows", F.col("__least").alias("component_id"))
    classes = linked.join(least, ["root", "__part"]).select("fp", "__rows", "component_id").unionByName(alone)
    return join_uneven(docs, written(classes), "fp", "__rows", docs.count()).select(F.col("__key").alias(key), "fp", "component_id")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_copies(documents(spark, sf_dir)).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame, words: int = WORDS, radius: int = RADIUS) -> DataFrame:
    """The rows of ``docs`` (doc_id, text and more) with the least id of each group of near copies, with its columns.

    Repeated rows of an id count once. Rows without an id can't be told apart by it and stay.
    """
    return least_of_each(docs, near_copies(docs, words=words, radius=radius))


def least_of_each(docs: DataFrame, found: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose id is the least one of its group in ``found`` (doc_id, component_id)."""
    n = free_name(docs, "__n")
    found = found.where("doc_id is not null")
    ids = durable(found.groupBy("doc_id").agg(F.min("component_id").alias("__least"), F.count(F.lit(1)).alias(n)).where("doc_id = __least").select("doc_id", n))
    kept = docs.join(ids, "doc_id").select(*docs.columns, n)
    out = kept.where(F.col(n) == 1)
    if not ids.where(F.col(n) > 1).isEmpty():
        out = out.unionByName(kept.where(F.col(n) > 1).dropDuplicates(["doc_id"]))
    return out.drop(n).unionByName(docs.where("doc_id is null"))
