"""Packing token sequences into fixed windows by best-fit decreasing.

Overlong documents are first cut into full windows. Pieces of one length are interchangeable, so the packing runs over
the histogram of lengths (at most ``window`` entries, whatever the input): a segment tree indexed by remaining capacity
finds the tightest open window, and a whole run of equal pieces goes into a whole run of equal windows at once. That
gives exactly the windows that placing the pieces one by one, longest first, gives. The pieces then find their places
by their rank among the pieces of their length.
"""

from __future__ import annotations

import itertools
import re
import zlib
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, ascii_words, documents, durable, making_room, rank_within

WINDOW = 2048
END_ID = 1
CACHE_WORDS = 400_000
BUCKETS = 1024


class TightestFit:
    """A segment tree over capacities 0..most: which of them have open windows."""

    def __init__(self, most: int):
        self.leaves = 1 << most.bit_length()
        self.any = [False] * (2 * self.leaves)

    def set(self, capacity: int, filled: bool) -> None:
        at = capacity + self.leaves
        self.any[at] = filled
        while at > 1:
            at //= 2
            self.any[at] = self.any[2 * at] or self.any[2 * at + 1]

    def least(self, capacity: int) -> int | None:
        """The smallest filled capacity that is at least ``capacity``."""
        at = capacity + self.leaves
        if not self.any[at]:
            while at > 1 and (at & 1 or not self.any[at + 1]):
                at //= 2
            if at <= 1:
                return None
            at += 1
            while at < self.leaves:
                at = 2 * at if self.any[2 * at] else 2 * at + 1
        return at - self.leaves


@dataclass
class Placements:
    """Runs of equal pieces: piece ``rank + j`` of ``length`` is number ``j % per`` from ``offset`` in window ``first + j // per``."""

    length: list[int] = field(default_factory=list)
    rank: list[int] = field(default_factory=list)
    per: list[int] = field(default_factory=list)
    first: list[int] = field(default_factory=list)
    offset: list[int] = field(default_factory=list)
    windows: int = 0

    def add(self, *row: int) -> None:
        for column, value in zip((self.length, self.rank, self.per, self.first, self.offset), row, strict=True):
            column.append(value)


def best_fit_decreasing(histogram: dict[int, int], window: int = WINDOW) -> Placements:
    """Pack ``histogram[length]`` pieces of each length (1..window) into windows."""
    tree, out = TightestFit(window), Placements()
    open_runs: dict[int, list[tuple[int, int]]] = {}  # capacity -> runs of windows (first, count)

    def leave(capacity: int, first: int, count: int) -> None:
        if capacity and count:
            runs = open_runs.setdefault(capacity, [])
            if not runs:
                tree.set(capacity, True)
            runs.append((first, count))

    for length in sorted((k for k, n in histogram.items() if n), reverse=True):
        left, rank = histogram[length], 0
        while left:
            capacity = tree.least(length)
            per = (window if capacity is None else capacity) // length
            if capacity is None:
                capacity, first, count = window, out.windows, -(-left // per)
                out.windows += count
            else:
                runs = open_runs[capacity]
                first, count = runs.pop()
                if not runs:
                    tree.set(capacity, False)
            whole = min(count, left // per)
            if whole:
                out.add(length, rank, per, first, window - capacity)
                leave(capacity - per * length, first, whole)
                rank, left = rank + whole * per, left - whole * per
            if whole < count and left:  # fewer than ``per`` are left
                out.add(length, rank, left, first + whole, window - capacity)
                leave(capacity - left * length, first + whole, 1)
                rank, left, whole = rank + left, 0, whole + 1
            leave(capacity, first + whole, count - whole)
    return out


#: Words of visible ASCII and precomposed Latin letters only: composition, case and classes of characters are plain here.
PLAIN = re.compile("[!-~\u00a1-\u024f]+")
PRE_TOKEN = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+")  # fixed value of the vocabulary file
WORD_END = b"\xff"  # stands for the vocabulary's mark of a word's end; no UTF-8 text has this byte


def byte_of_letter() -> dict[str, int]:
    """Byte-level vocabularies write bytes as letters: visible ones as themselves, the others in order from U+0100."""
    visible = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    hidden = [b for b in range(256) if b not in visible]
    return {chr(b): b for b in visible} | {chr(256 + k): b for k, b in enumerate(hidden)}


class WordTokenizer(dict):
    """From white-space-delimited words to their token ids; words are kept, a bounded number of them.

    The pre-tokenizer never joins characters across ASCII white space and the normaliser neither, so a text's ids are
    its words' ids in a row. Plain words go through a compiled merge table made of the same vocabulary, whose ids are in
    the order of its merges; all others go through the tokenizer itself.
    """

    def __init__(self, path: str):
        import tiktoken
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        letters = byte_of_letter()
        ranks = {}
        for token, rank in self.tokenizer.get_vocab(with_added_tokens=False).items():
            end = token.endswith("</w>") and len(token) > 4
            ranks[bytes(letters[c] for c in (token[:-4] if end else token)) + WORD_END * end] = rank
        self.merge = tiktoken.Encoding("words", pat_str=r"\S+", mergeable_ranks=ranks, special_tokens={}).encode_single_piece if hasattr(tiktoken.Encoding, "encode_single_piece") else tiktoken.Encoding("words", pat_str=r"\S+", mergeable_ranks=ranks, special_tokens={})._encode_single_piece

    def __missing__(self, word: str) -> list[int]:
        if PLAIN.fullmatch(word) and "<|" not in word:
            ids = []
            for part in PRE_TOKEN.findall(word.lower()):
                ids += self.merge(part.encode() + WORD_END)
        else:
            ids = self.tokenizer.encode(word, add_special_tokens=False).ids
        if len(self) >= CACHE_WORDS:
            self.clear()
        self[word] = ids
        return ids

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All ids of all texts (null: empty), and where each text's ids start, with the end of the last."""
        counts, words = ascii_words(texts, lower=False)
        if not len(words):
            return np.zeros(0, "<u4"), np.zeros(len(counts) + 1, "i8")
        coded = words.dictionary_encode()
        codes = coded.indices.to_numpy()
        lists = [self[w] for w in coded.dictionary.to_pylist()]
        sizes = np.fromiter(map(len, lists), "i8", len(lists))
        flat = np.fromiter(itertools.chain.from_iterable(lists), "<u4", int(sizes.sum()))
        starts = np.cumsum(sizes) - sizes
        each = sizes[codes]
        ends = np.cumsum(each)
        ids = flat[np.repeat(starts[codes] - (ends - each), each) + np.arange(ends[-1])]
        return ids, np.concatenate([[0], ends])[np.concatenate([[0], np.cumsum(counts)])]


TOKENIZERS: dict[str, WordTokenizer] = {}


def tokenizer(path: str) -> WordTokenizer:
    """One for each worker process."""
    if path not in TOKENIZERS:
        TOKENIZERS[path] = WordTokenizer(path)
    return TOKENIZERS[path]


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def pieces(df: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, window: int = WINDOW, keep_ids: bool = False) -> DataFrame:
    """Tokenize each text (null: empty), append the end id, and cut it into full windows and a rest.

    One row for each piece: key, start, length, ids_crc32, doc_tokens and, with ``keep_ids``, the ids.
    """
    path = path or default_path()

    def rows(batches):
        for batch in batches:
            keys, out = [], []
            ids, bounds = tokenizer(path).encode(batch.column(1))
            for row, (a, b) in enumerate(itertools.pairwise(bounds.tolist())):
                coded = ids[a:b].tobytes() + END_ID.to_bytes(4, "little")
                for at in range(0, len(coded), 4 * window):
                    part = coded[at : at + 4 * window]
                    keys.append(row)
                    out.append((at // 4, len(part) // 4, zlib.crc32(part), len(coded) // 4, *[np.frombuffer(part, "<u4").astype("i4")] * keep_ids))
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), *[pa.list_(pa.int32())] * keep_ids]
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(keys)), *[pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)]], [key, "start", "length", "ids_crc32", "doc_tokens", *["ids"] * keep_ids])

    narrow = df.select(df[key], df[text])
    return arrow_map(narrow, rows, f"`{key}` {narrow.schema[0].dataType.simpleString()}, start long, length long, ids_crc32 long, doc_tokens long" + ", ids array<int>" * keep_ids)


def pack(cut: DataFrame, key: str = "doc_id", window: int = WINDOW, store: Callable[[DataFrame], DataFrame] = durable) -> DataFrame:
    """Give each piece (a row of ``pieces``; other columns stay) its sequence_id and offset.

    Sequences are filled from offset 0 without gaps. Empty input gives no rows; equal rows get places of their own.
    The histogram that comes to the driver has at most ``window`` rows; the runs of placements are bounded by it.
    ``store`` cuts the lineage of the pieces; ``written`` takes less disk where they hold their ids.
    """
    cut = store(making_room(cut, ["sequence_id", "offset", "__rank"]))
    histogram = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    placed = best_fit_decreasing(histogram, window)
    length, rank, per, first, offset = (np.array(c, "i8") for c in (placed.length, placed.rank, placed.per, placed.first, placed.offset))
    # Placements come by descending length and ascending rank; one number orders both.
    span = max([1, *histogram.values()]) + 1
    order = (window - length) * span + rank

    def rows(batches):
        for batch in batches:
            size, at = (batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("length", "__rank"))
            run = np.searchsorted(order, (window - size) * span + at, "right") - 1
            step = at - rank[run]
            kept = batch.drop_columns(["__rank"])
            yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(first[run] + step // per[run]), pa.array(offset[run] + step % per[run] * size)], [*kept.schema.names, "sequence_id", "offset"])

    ranked = rank_within(cut, ["length"], [key, "start", "ids_crc32"], "__rank", BUCKETS)
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in cut.schema.fields)
    return arrow_map(ranked, rows, f"{fields}, sequence_id long, offset long")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(pieces(documents(spark, sf_dir)))
