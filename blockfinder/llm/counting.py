"""Token counts that follow edits: a segment tree over each document's pre-tokens.

A document's text falls into pre-tokens, which are encoded one by one, so its count is the sum of theirs. A tree keeps
the characters and tokens below each node. An edit encodes anew only from the pre-token before it to where the old
and the new cuts meet again, and updates the sums on the way to the root.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterable
from dataclasses import dataclass

import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, documents

LEAF = 64  # pre-tokens of a leaf when a tree is built; it is split beyond twice as many
CACHE_WORDS = 200_000
SLICE = 4 << 20
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"  # fixed value of the vocabulary file
PRE_TOKEN = regex.compile(PATTERN)
CONTEXT = 3  # characters ahead that a cut can depend on, besides a run of white space


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


class Counter(dict):
    """Tokens of a pre-token; pre-tokens are kept, a bounded number of them."""

    def __init__(self, path: str):
        import base64

        import tiktoken

        with open(path, "rb") as file:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, file)}
        self.encode = tiktoken.Encoding("counted", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})._encode_single_piece

    def __missing__(self, piece: str) -> int:
        if len(self) >= CACHE_WORDS:
            self.clear()
        self[piece] = n = len(self.encode(piece.encode()))
        return n


COUNTERS: dict[str, Counter] = {}


def counter(path: str) -> Counter:
    """One for each worker process."""
    if path not in COUNTERS:
        COUNTERS[path] = Counter(path)
    return COUNTERS[path]


@dataclass(slots=True)
class Leaf:
    """Some pre-tokens in a row: their lengths in characters and their tokens."""

    sizes: list[int]
    tokens: list[int]


class CountTree:
    """The counts of one document. ``sums[k]``: (characters, tokens) below node k; the leaves follow the inner nodes."""

    def __init__(self, text: str, count: Counter, leaf: int = LEAF):
        self.count, self.leaf, self.text = count, leaf, text
        pieces = PRE_TOKEN.findall(text)
        self.encoded = 0  # characters encoded anew by edits
        self.touched = 0  # nodes whose sums were updated by edits
        self.leaves = [Leaf(list(map(len, p)), [count[x] for x in p]) for p in itertools.batched(pieces, leaf)]
        self.build()

    @classmethod
    def restore(cls, text: str, sizes: list[int], tokens: list[int], count: Counter, leaf: int = LEAF) -> CountTree:
        """From stored pre-token sizes and counts, without encoding."""
        out = cls("", count, leaf)
        out.text = text
        out.leaves = [Leaf(list(s), list(t)) for s, t in zip(itertools.batched(sizes, leaf), itertools.batched(tokens, leaf), strict=True)]
        out.build()
        return out

    def build(self) -> None:
        n = self.width = 1 << max(0, len(self.leaves) - 1).bit_length()
        self.chars = [0] * n + [sum(x.sizes) for x in self.leaves] + [0] * (n - len(self.leaves))
        self.tokens = [0] * n + [sum(x.tokens) for x in self.leaves] + [0] * (n - len(self.leaves))
        for k in range(n - 1, 0, -1):
            self.chars[k] = self.chars[2 * k] + self.chars[2 * k + 1]
            self.tokens[k] = self.tokens[2 * k] + self.tokens[2 * k + 1]

    @property
    def total(self) -> int:
        return self.tokens[1]

    def locate(self, at: int) -> tuple[int, int, int]:
        """The leaf and the place in it of the pre-token that holds character ``at``, and where that begins."""
        if not self.leaves:
            return 0, 0, 0
        at = min(at, max(0, len(self.text) - 1))
        node, begins = 1, 0
        while node < self.width:
            node *= 2
            if at >= begins + self.chars[node]:
                begins += self.chars[node]
                node += 1
        k = min(node - self.width, len(self.leaves) - 1)
        for j, size in enumerate(self.leaves[k].sizes):
            if at < begins + size:
                return k, j, begins
            begins += size
        return k, len(self.leaves[k].sizes), begins

    def context(self, start: int) -> tuple[int, int, int]:
        """The last pre-token that begins at least ``CONTEXT`` characters before ``start`` and behind no white space."""
        k, j, begins = self.locate(start)
        while begins and (begins > start - CONTEXT or self.text[begins - 1].isspace()):
            if j == 0:
                k -= 1
                j = len(self.leaves[k].sizes)
            else:
                j -= 1
                begins -= self.leaves[k].sizes[j]
        return k, j, begins

    def edit(self, start: int, end: int, new: str) -> None:
        """Put ``new`` in the place of the characters from ``start`` to ``end``; both are cut to the text."""
        start = max(0, min(start, len(self.text)))
        end = max(start, min(end, len(self.text)))
        old_length = len(self.text)
        k, j, begins = self.context(start)
        self.text = self.text[:start] + new + self.text[end:]
        shift = len(new) - (end - start)
        # Old cuts behind the edit, from which both texts are the same; the first that the new cuts meet ends the work.
        cuts = self.old_cuts(k, j, begins, end)
        old = next(cuts, (old_length, len(self.leaves), 0))
        sizes, tokens, at = [], [], begins
        settled = 0
        while at < len(self.text):
            piece = PRE_TOKEN.match(self.text, at).group()
            sizes.append(len(piece))
            tokens.append(self.count[piece])
            at += len(piece)
            while old[0] + shift < at and old[0] < old_length:
                old = next(cuts, (old_length, len(self.leaves), 0))
            # A run of white space is cut by what follows it: one more piece must agree behind the edit.
            settled = settled + 1 if old[0] + shift == at and old[0] >= end else 0
            if settled and at > start + len(new) and not piece.isspace():
                break
        else:
            old = (old_length, len(self.leaves), 0)
        self.encoded += at - begins
        self.splice(k, j, *old[1:], sizes, tokens)

    def old_cuts(self, k: int, j: int, begins: int, end: int):
        """(where it ends, leaf and place behind it) of the old pre-tokens from (k, j) on that end at or behind ``end``."""
        while k < len(self.leaves):
            sizes = self.leaves[k].sizes
            while j < len(sizes):
                begins += sizes[j]
                j += 1
                if begins >= end:
                    yield begins, k, j
            k, j = k + 1, 0

    def splice(self, k: int, j: int, last: int, behind: int, sizes: list[int], tokens: list[int]) -> None:
        """Replace the pre-tokens from (k, j) to before (last, behind)."""
        if not self.leaves:
            self.leaves = [Leaf(list(a), list(b)) for a, b in zip(itertools.batched(sizes, self.leaf), itertools.batched(tokens, self.leaf), strict=True)]
            self.build()
            self.touched += 2 * self.width
            return
        tail = self.leaves[last] if last < len(self.leaves) else Leaf([], [])
        first = self.leaves[k]
        joined = Leaf(first.sizes[:j] + sizes + tail.sizes[behind:], first.tokens[:j] + tokens + tail.tokens[behind:])
        upto = min(last, len(self.leaves) - 1)
        if len(joined.sizes) <= 2 * self.leaf:
            self.leaves[k] = joined
            for n in range(k + 1, upto + 1):
                self.leaves[n] = Leaf([], [])
            changed = range(k, upto + 1)
            for n in changed:
                self.chars[self.width + n], self.tokens[self.width + n] = sum(self.leaves[n].sizes), sum(self.leaves[n].tokens)
            nodes = {self.width + n for n in changed}
            while nodes and nodes != {1}:
                self.touched += len(nodes)
                nodes = {n // 2 for n in nodes if n > 1}
                for n in nodes:
                    self.chars[n] = self.chars[2 * n] + self.chars[2 * n + 1]
                    self.tokens[n] = self.tokens[2 * n] + self.tokens[2 * n + 1]
        else:
            self.leaves[k : upto + 1] = [Leaf(list(a), list(b)) for a, b in zip(itertools.batched(joined.sizes, self.leaf), itertools.batched(joined.tokens, self.leaf), strict=True)]
            self.build()
            self.touched += 2 * self.width

    def pre_tokens(self) -> tuple[list[int], list[int]]:
        return [s for x in self.leaves for s in x.sizes], [t for x in self.leaves for t in x.tokens]


def build_trees(df: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None) -> DataFrame:
    """The stored form: (key, text, n_tokens, sizes, tokens), each pre-token's characters and tokens. Null counts as empty."""
    path = path or default_path()

    def rows(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            count = counter(path)
            texts = [t or "" for t in batch.column(1).to_pylist()]
            pieces = [PRE_TOKEN.findall(t) for t in texts]
            tokens = [[count[x] for x in p] for p in pieces]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts), pa.array(list(map(sum, tokens)), pa.int64()), pa.array([list(map(len, p)) for p in pieces], pa.list_(pa.int32())), pa.array(tokens, pa.list_(pa.int32()))], [key, text, "n_tokens", "sizes", "tokens"])

    narrow = df.select(df[key], df[text])
    return arrow_map(narrow, rows, f"`{key}` {narrow.schema[0].dataType.simpleString()}, `{text}` string, n_tokens long, sizes array<int>, tokens array<int>", SLICE)


EDITS = "array<struct<start:int,stop:int,new:string>>"


def apply_edits(trees: DataFrame, key: str = "doc_id", text: str = "text", edits: str = "edits", path: str | None = None) -> DataFrame:
    """Apply each row's ``edits`` (start, stop, new; in characters of the text as the edits before have left it).

    Gives (key, n_tokens, n_tokens_edited, n_edits, n_chars_edited, chars_encoded, nodes_updated, text, sizes, tokens).
    Null edits are none; null in an edit counts as 0 or empty; places beyond the text are cut to it.
    """
    path = path or default_path()
    names = [key, "n_tokens", "n_tokens_edited", "n_edits", "n_chars_edited", "chars_encoded", "nodes_updated", text, "sizes", "tokens"]

    def rows(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            out = []
            for old, sizes, tokens, changes in zip(*[batch.column(k).to_pylist() for k in (2, 3, 4, 5)], strict=True):
                tree = CountTree.restore(old or "", sizes or [], tokens or [], counter(path))
                for e in changes or []:
                    if e is not None:
                        tree.edit(e["start"] or 0, e["stop"] or 0, e["new"] or "")
                sizes, tokens = tree.pre_tokens()
                out.append((tree.total, len(changes or []), len(tree.text), tree.encoded, tree.touched, tree.text, sizes, tokens))
            kinds = [pa.int64()] * 5 + [pa.string(), pa.list_(pa.int32()), pa.list_(pa.int32())]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *[pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)]], names)

    narrow = trees.select(key, "n_tokens", text, "sizes", "tokens", F.col(edits).cast(EDITS).alias("edits"))
    return arrow_map(narrow, rows, f"`{key}` {narrow.schema[0].dataType.simpleString()}, n_tokens long, n_tokens_edited long, n_edits long, n_chars_edited long, chars_encoded long, nodes_updated long, `{text}` string, sizes array<int>, tokens array<int>", SLICE)


def trial_edits(key: str = "doc_id", text: str = "text"):
    """Three edits of each document at places drawn from its id: an insertion, a deletion and a replacement."""
    n = F.length(text)

    def place(k: int):
        return F.pmod(F.xxhash64(F.lit(k), F.col(key)), F.greatest(n, F.lit(1)).cast("long")).cast("int")

    edits = [(place(1), F.lit(0), F.lit(" revised wording,")), (place(2), F.lit(24), F.lit("")), (place(3), F.lit(6), F.lit("it's 2x"))]
    return F.array(*[F.struct(at.alias("start"), (at + size).alias("stop"), new.alias("new")) for at, size, new in edits])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    trees = build_trees(documents(spark, sf_dir)).withColumn("edits", trial_edits())
    edited = apply_edits(trees)
    return edited.select("doc_id", "n_tokens", "n_tokens_edited", "n_edits", "n_chars_edited", "chars_encoded", "nodes_updated", F.crc32("text").alias("text_crc32"))
