"""SentencePiece encoding and decoding as a relational lattice.

Texts are cut into words that no piece of the vocabulary crosses: between two characters that are no piece themselves and
not side by side in a longer one together with either neighbour. For the distinct words of the whole table, substrings
up to the length of the longest piece that begins like them are exploded and joined to the piece table; a word's matches are the edges of its
lattice. They are grouped by word, and a fold over the positions keeps, for each, the best way to it (Viterbi); the way
back gives the word's ids. The words are dealt out once, finely enough for a task to hold its lattices in memory; edges
stay where their word is. Frequent words, a bounded number, are then looked up in place; a text's other words are joined
to their ids and meet the text again by a hash of its key and itself.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterable
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, crc_text, documents, frequent, making_room, written

SPACE = "▁"  # fixed value: how the vocabulary writes a space
BLOCK = 64  # positions that are folded over the same edges
HEAD = 1 << 19  # most words that are looked up in place
HEAD_BYTES = 48
UNKNOWN_COST = 10.0  # below the least score of a piece, for each character that no piece has
NO_PIECE = -1e8  # scores below this mark pieces that are never preferred
SLICE = 3 << 20
PACKED_SLICE = 1 << 20
WORDS_A_TASK = 8192
MARKS = 1 << 22
FACTORS = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D], "u4")
NO_ID = -1
FIRST = 4  # characters that tell how long a piece that begins with them can be


@dataclass
class Pieces:
    """The vocabulary: each id's piece and score, whether it takes part in encoding, and the ids of single bytes."""

    text: list[str]
    score: list[float]
    normal: list[bool]
    byte_ids: list[int]

    @classmethod
    def load(cls, path: str) -> Pieces:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        ids = range(model.get_piece_size())
        text = [model.id_to_piece(i) for i in ids]
        normal = [not (model.is_unknown(i) or model.is_control(i) or model.is_byte(i) or model.is_unused(i)) for i in ids]
        at = {t: i for i, t in enumerate(text)}
        return cls(text, [model.get_score(i) for i in ids], normal, [at.get(f"<0x{b:02X}>", model.unk_id()) for b in range(256)])

    @cached_property
    def longest(self) -> int:
        return max(len(t) for t, n in zip(self.text, self.normal, strict=True) if n)

    @cached_property
    def least(self) -> float:
        return min(s for s, n in zip(self.score, self.normal, strict=True) if n and s > NO_PIECE)

    @cached_property
    def neighbours(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Each code point's class (0: in no longer piece), marks of pairs that are pieces, marks of threes in a row in some piece.

        Marks are kept by a hash; two that meet there only leave words longer than they need be.
        """
        long = [t for t, n in zip(self.text, self.normal, strict=True) if n and len(t) > 1]
        sizes = np.fromiter(map(len, long), "i8", len(long))
        points = np.frombuffer("".join(long).encode("utf-32-le"), "u4")
        chars = np.unique(points)
        kind = np.zeros(0x110000, "u4")
        kind[chars] = np.arange(1, len(chars) + 1)
        first = np.cumsum(sizes) - sizes
        kinds = kind[points]
        pairs, threes = np.zeros(MARKS, bool), np.zeros(MARKS, bool)
        two = first[sizes == 2]
        pairs[mark(kinds[two], kinds[two + 1])] = True
        inner = np.ones(len(points), bool)
        inner[first] = inner[first + sizes - 1] = False
        middle = np.flatnonzero(inner)
        threes[mark(kinds[middle - 1], kinds[middle], kinds[middle + 1])] = True
        return kind, pairs, threes

    def table(self, spark: SparkSession) -> DataFrame:
        rows = [(t, i, s) for i, (t, s, n) in enumerate(zip(self.text, self.score, self.normal, strict=True)) if n]
        return spark.createDataFrame(rows, "piece string, id int, score double")

    def table_of_bytes(self, space: str) -> pa.Array:
        """The bytes of each id, with its spaces written as ``space``, and a last row without any."""
        byte = {i: bytes([b]) for b, i in enumerate(self.byte_ids) if self.text[i] == f"<0x{b:02X}>"}
        rows = [byte.get(i, t.replace(SPACE, space).encode() if n else b"") for i, (t, n) in enumerate(zip(self.text, self.normal, strict=True))]
        return pa.array([*rows, b""], pa.large_binary())

    def normalise(self, text: str | None) -> str:
        return SPACE + text.replace(" ", SPACE) if text else ""


def mark(*kinds: np.ndarray) -> np.ndarray:
    """The place of a sequence of classes among ``MARKS``."""
    code = kinds[0] * FACTORS[0]
    for k, factor in zip(kinds[1:], FACTORS[1:], strict=False):
        code += k * factor
    code >>= np.uint32(33 - MARKS.bit_length())
    return code


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def lattice(words: DataFrame, pieces: Pieces) -> DataFrame:
    """The edges of each word's lattice: (word, n, length, start, stop, score, id).

    A character without a piece of its own gets an edge with ``NO_ID`` that stands for its UTF-8 bytes.
    """
    length = F.length("word")
    starts = words.select("word", "n", length.alias("length"), F.explode(F.sequence(F.lit(0), length - 1)).alias("start"))
    starts = starts.withColumn("head", F.col("word").substr(F.col("start") + 1, F.lit(FIRST)))
    reach = pieces.table(words.sparkSession).where(F.length("piece") >= FIRST).groupBy(F.substring("piece", 1, FIRST).alias("head")).agg(F.max(F.length("piece")).alias("most"))
    starts = starts.join(F.broadcast(reach), "head", "left")
    most = F.least(F.coalesce("most", F.lit(FIRST - 1)), F.col("length") - F.col("start"))
    spans = starts.select("word", "n", "length", "start", F.explode(F.sequence(F.lit(1), most)).alias("size"))
    subs = spans.withColumn("piece", F.col("word").substr(F.col("start") + 1, F.col("size")))
    found = subs.join(F.broadcast(pieces.table(words.sparkSession)), "piece", "left").where("id is not null or size = 1")
    score = F.coalesce("score", F.lit(pieces.least - UNKNOWN_COST)).alias("score")
    return found.select("word", "n", "length", "start", (F.col("start") + F.col("size")).alias("stop"), score, F.coalesce("id", F.lit(NO_ID)).alias("id"))


def bytes_of(piece: Column, pieces: Pieces) -> Column:
    """The ids that stand for a character's UTF-8 bytes."""
    table = F.array(*[F.lit(i) for i in pieces.byte_ids])
    hexed = F.hex(F.encode(piece, "UTF-8"))
    return F.transform(F.sequence(F.lit(1), F.length(hexed) - 1, F.lit(2)), lambda k: F.element_at(table, F.conv(F.substring(hexed, k, F.lit(2)), 16, 10).cast("int") + 1))


def viterbi(edges: DataFrame, pieces: Pieces) -> DataFrame:
    """The best way through each word's lattice: (word, n, ids).

    The fold goes over blocks of positions and carries only the last ``longest`` of them from block to block, next to the
    list of each position's best score, where its last edge starts and which piece that is. Of equal
    ways the one with the shorter last piece is taken.
    """
    block = F.floor((F.col("stop") - 1) / BLOCK).cast("int")
    blocks = edges.groupBy("word", "n", "length", block.alias("block")).agg(F.collect_list(F.struct("start", "stop", "score", "id")).alias("edges"))
    words = blocks.groupBy("word", "n", "length").agg(F.array_sort(F.collect_list(F.struct("block", "edges"))).alias("blocks"))
    longest = pieces.longest
    ways = "array<struct<score:double,start:int,id:int>>"
    begin = F.array(F.struct(F.lit(0.0), F.lit(0), F.lit(NO_ID))).cast(ways)
    state = F.struct(begin.alias("last"), F.array().cast(ways).alias("best"))

    def over_block(state, part):
        def over_position(known, stop):
            here = F.filter(part["edges"], lambda e: e["stop"] == stop)
            return F.concat(known, F.array(F.array_max(F.transform(here, lambda e: F.struct((F.element_at(known, e["start"] - stop)["score"] + e["score"]).alias("score"), e["start"].alias("start"), e["id"].alias("id")))))).cast(ways)

        stops = F.sequence(part["block"] * BLOCK + 1, F.least(F.col("length"), (part["block"] + 1) * BLOCK))
        known = F.aggregate(stops, state["last"], over_position)
        return F.aggregate(
            F.array(known),
            state,
            lambda held, all_: F.struct(F.slice(all_, F.greatest(F.lit(1), F.size(all_) - longest + 1), longest).alias("last"), F.concat(held["best"], F.slice(all_, F.size(held["last"]) + 1, F.size(all_))).alias("best")),
        )

    folded = words.select("word", "n", "length", F.aggregate("blocks", state, over_block)["best"].alias("best"))

    def step_back(state, stop):
        edge = F.element_at(state["best"], stop)
        return F.when(stop == state["at"], F.struct(edge["start"].alias("at"), F.concat(state["parts"], F.array(F.struct(edge["start"], edge["id"]))).alias("parts"), state["best"].alias("best"))).otherwise(state)

    parts = F.array().cast("array<struct<start:int,id:int>>").alias("parts")
    back = F.aggregate(F.sequence(F.col("length"), F.lit(1), F.lit(-1)), F.struct(F.col("length").alias("at"), parts, F.col("best").alias("best")), step_back)
    found = folded.select("word", "n", F.reverse(back["parts"]).alias("parts"))
    known = ~F.exists("parts", lambda p: p["id"] == NO_ID)
    other = F.flatten(F.transform("parts", lambda p: F.when(p["id"] != NO_ID, F.array(p["id"])).otherwise(bytes_of(F.col("word").substr(p["start"] + 1, F.lit(1)), pieces))))
    return found.select("word", "n", F.when(known, F.col("parts.id")).otherwise(other).alias("ids"))


def distinct_words(df: DataFrame, text: str, pieces: Pieces) -> DataFrame:
    """(word, n) of all texts."""

    def rows(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            found = cut_words(batch.column(0).to_pylist(), pieces)[1].value_counts()
            yield pa.RecordBatch.from_arrays([found.field("values").cast(pa.string()), found.field("counts")], ["word", "n"])

    return arrow_map(df.select(text), rows, "word string, n long", SLICE).groupBy("word").agg(F.sum("n").alias("n"))


def cut_words(texts: list[str | None], pieces: Pieces) -> tuple[np.ndarray, pa.Array]:
    """The number of words of each text, and all words."""
    kind, pairs, threes = pieces.neighbours
    whole = [pieces.normalise(t) for t in texts]
    sizes = np.fromiter(map(len, whole), "i8", len(whole))
    first = np.cumsum(sizes) - sizes
    joined = "".join(whole)
    points = np.frombuffer(joined.encode("utf-32-le"), "u4")
    kinds = kind[points]
    middle = np.zeros(len(points), bool)
    middle[1:-1] = threes[mark(kinds[:-2], kinds[1:-1], kinds[2:])]
    middle[first[sizes > 0]] = middle[(first + sizes - 1)[sizes > 0]] = False
    begins = np.ones(len(points), bool)
    begins[1:] = ~(pairs[mark(kinds[:-1], kinds[1:])] | middle[:-1] | middle[1:])
    begins[first[sizes > 0]] = True
    places = np.flatnonzero(begins)
    width = (points > 0x7F).astype("u1") + (points > 0x7FF) + (points > 0xFFFF) + np.uint8(1)
    offsets = np.r_[0, np.cumsum(np.add.reduceat(width, places, dtype="i8"))] if len(places) else np.zeros(1, "i8")
    words = pa.LargeStringArray.from_buffers(len(places), pa.py_buffer(offsets), pa.py_buffer(joined.encode()))
    return np.searchsorted(places, first + sizes) - np.searchsorted(places, first), words


def lists_flat(lists: pa.Array) -> np.ndarray:
    return lists.flatten().to_numpy(zero_copy_only=False).astype("i4")


def lists_starts(lists: pa.Array) -> np.ndarray:
    """Where each list begins in the flat values."""
    sizes = list_sizes(lists)
    return np.cumsum(sizes) - sizes


def list_sizes(lists: pa.Array) -> np.ndarray:
    return pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False).astype("i8")


def encode(df: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, back: str | None = None) -> DataFrame:
    """(key, text, ids, n_tokens) of every row; null and empty texts have no ids, and null stays null.

    ``back`` names a further column with what ``decode`` makes of the ids, in the same pass.

    Repeated rows stay. A word is held as a whole, so memory grows with the longest run without a space.
    """
    pieces = Pieces.load(path or default_path())
    words = written(distinct_words(df, text, pieces))
    dealt = words.repartition(max(1, -(-words.count() // WORDS_A_TASK)), "word")
    coded = written(viterbi(lattice(dealt, pieces), pieces))
    most = frequent(coded, "word", "n", HEAD, HEAD_BYTES)
    table = coded.where(most).select("word", "ids").toArrow() if most is not None else coded.limit(0).select("word", "ids").toArrow()
    head_words, head_ids = table["word"].combine_chunks().cast(pa.large_string()), table["ids"].combine_chunks()

    # Should two texts share a print, each finds the other's words beside its own, which does no harm.
    narrow = df.select(F.col(key).alias("key"), F.xxhash64(key, text).alias("print"), F.col(text).alias("text"))
    kind = narrow.schema["key"].dataType.simpleString()

    def rare(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            sizes, words = cut_words(batch.column(1).to_pylist(), pieces)
            named = words.dictionary_encode()
            which = named.indices.to_numpy()
            other = pc.index_in(named.dictionary, value_set=head_words).is_null().to_numpy(zero_copy_only=False)[which]
            row = np.repeat(np.arange(batch.num_rows), sizes)[other]
            once = np.unique(row * max(1, len(named.dictionary)) + which[other])
            row, word = (pa.array(x) for x in np.divmod(once, max(1, len(named.dictionary))))
            yield pa.RecordBatch.from_arrays([batch.column(0).take(row), named.dictionary.take(word).cast(pa.string())], ["print", "word"])

    def packed(batches: Iterable[pa.RecordBatch]):
        squeeze = zstandard.ZstdCompressor(level=3)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([None if t is None else squeeze.compress(t.encode()) for t in batch.column(2).to_pylist()], pa.binary())], ["key", "print", "packed"])

    others = coded if most is None else coded.where(~most)
    own = arrow_map(narrow.select("print", "text"), rare, "print long, word string", SLICE).join(others.select("word", "ids"), "word").select("print", "ids")
    own = own.groupBy("print").agg(F.collect_set("ids").alias("rare"))
    texts = arrow_map(narrow, packed, f"key {kind}, print long, packed binary", SLICE)
    both = texts.alias("t").join(own.alias("r"), F.col("t.print") == F.col("r.print"), "left").select("t.key", "t.packed", "r.rare")

    def assemble(batches: Iterable[pa.RecordBatch]):
        expand = zstandard.ZstdDecompressor()
        spelled, plain = pieces.table_of_bytes(SPACE), pieces.table_of_bytes(" ")
        head_flat, head_first, head_long = lists_flat(head_ids), lists_starts(head_ids), list_sizes(head_ids)
        for batch in batches:
            texts = [None if blob is None else expand.decompress(blob).decode() for blob in batch.column(1).to_pylist()]
            sizes, words = cut_words(texts, pieces)
            coded = words.dictionary_encode()
            rare_ids = batch.column(2).flatten()
            rare_words = joined_pieces(rare_ids, spelled).cast(pa.large_string())
            here = pc.index_in(coded.dictionary, value_set=head_words)
            there = pc.index_in(coded.dictionary, value_set=rare_words)
            flat = np.concatenate([head_flat, lists_flat(rare_ids)])
            first = np.concatenate([head_first, lists_starts(rare_ids) + len(head_flat)])
            long = np.concatenate([head_long, list_sizes(rare_ids)])
            of = pc.coalesce(here, pc.add(there, len(head_words))).to_numpy(zero_copy_only=False).astype("i8")[coded.indices.to_numpy()]
            each = long[of]
            ends = np.cumsum(each)
            ids = flat[np.repeat(first[of] - (ends - each), each) + np.arange(ends[-1] if len(ends) else 0)]
            bounds = np.r_[0, ends][np.r_[0, np.cumsum(sizes)]]
            lists = pa.ListArray.from_arrays(pa.array(bounds.astype("i4")), pa.array(ids.astype("i4")))
            found = [batch.column(0), pa.array(texts, pa.string()), lists, pa.array(np.diff(bounds))]
            yield pa.RecordBatch.from_arrays([*found, decoded(lists, plain)] if back else found, names)

    names = ["key", "text", "ids", "n_tokens", *([back] if back else [])]
    schema = f"key {kind}, text string, ids array<int>, n_tokens long" + (f", `{back}` string" if back else "")
    return arrow_map(both, assemble, schema, PACKED_SLICE).withColumnsRenamed({"key": key, "text": text})


def joined_pieces(lists: pa.Array, table: pa.Array) -> pa.Array:
    """The bytes that each list of ids stands for; ids out of range stand for nothing (the table's last row)."""
    flat = pc.fill_null(lists.flatten(), -1).to_numpy(zero_copy_only=False)
    none = len(table) - 1
    parts = table.take(pa.array(np.where((flat >= 0) & (flat < none), flat, none)))
    offsets = np.frombuffer(parts.buffers()[1], "i8")[: len(parts) + 1]
    bounds = offsets[np.r_[0, np.cumsum(list_sizes(lists))]]
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(lists), [None, pa.py_buffer(bounds), parts.buffers()[2] or pa.py_buffer(b"")])


def decoded(lists: pa.Array, table: pa.Array) -> pa.Array:
    texts = [b.decode("utf-8", "replace").removeprefix(" ") for b in joined_pieces(lists, table).to_pylist()]
    return pc.if_else(lists.is_valid(), pa.array(texts, pa.string()), pa.scalar(None, pa.string()))


def decode(df: DataFrame, ids: str = "ids", out: str = "decoded", path: str | None = None) -> DataFrame:
    """All rows and columns of ``df`` with the text that its ids stand for; null ids give null, ids out of range nothing.

    Byte pieces in a row are read as UTF-8, broken ones as replacement characters; the space put before a text goes.
    """
    pieces = Pieces.load(path or default_path())
    table = pieces.table_of_bytes(" ")
    df = making_room(df, [out])
    at, names = df.columns.index(ids), [*df.columns, out]

    def rows(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, decoded(batch.column(at), table)], names)

    return arrow_map(df, rows, ", ".join([*[f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields], f"`{out}` string"]), SLICE)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    coded = encode(documents(spark, sf_dir), back="decoded")
    return coded.select("doc_id", "n_tokens", "ids", crc_text(F.col("text")).alias("text_crc32"), crc_text(F.col("decoded")).alias("decoded_crc32"))
