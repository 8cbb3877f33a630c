"""Language identification by compression: the language whose dictionary makes a text smallest.

Each language has a raw-content dictionary of pieces of texts in it, from a bounded sample of labelled rows. A text is
compressed with each of them; the fewest bytes win. Narrow margins, relative to the compressed size, are rejected: rows
of the sample that are in no dictionary tell how wide they are for texts of a size.
"""

from __future__ import annotations

import re
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, as_bytes, crc_text, documents, making_room

DICTIONARY_BYTES = 32 << 10  # of sampled text for each language
PIECE_CHARS = 1024  # of a piece of a sampled text
PIECES = 4  # most pieces of a sampled text; second ones count only when all texts' first ones leave room
SAMPLE_ROWS = 400  # sampled texts of each language, in expectation
MOST_LANGUAGES = 1024  # a table with more distinct labels than this is refused, not cut
LEVEL = 3
NARROW = 0.5  # a score of at most this is rejected; it is that of a margin of ``LEAST_PART`` of the usual one
LEAST_PART = 0.25
KEPT_BACK = 8  # one of so many sampled texts is in no dictionary
ENOUGH = 20  # rows that the usual margin of a size is taken from, at least
USUAL = 0.08  # the usual margin if no row is left to tell
UNKNOWN = "und"
LETTER = re.compile(r"[^\W\d_]")
FOLD = bytes(c + 32 if 0x41 <= c <= 0x5A else c if c >= 0x80 or 0x61 <= c <= 0x7A else 0x20 for c in range(256))
SEARCH = {"min_match": 4, "strategy": zstandard.STRATEGY_GREEDY}
SHORT = 400  # bytes; shorter texts are compressed behind a sample of each language, where each byte counts
SAMPLE_BYTES = 1024


def plain(text: bytes) -> bytes:
    """What is compressed: words in lower case, without the marks and digits that all languages share."""
    return text.translate(FOLD)


def learn(docs: DataFrame, rows: int = SAMPLE_ROWS) -> dict[str, bytes]:
    """A dictionary of up to ``DICTIONARY_BYTES`` for each non-null language of ``docs`` (text, lang, doc_id).

    Texts are taken by a hash of their id at a rate that gives about ``rows`` of each language, so what comes to the
    driver is bounded by the number of languages. Null texts teach nothing.
    """
    labelled = docs.where("lang is not null and text is not null")
    sizes = {r["lang"]: r["n"] for r in labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy("lang").limit(MOST_LANGUAGES + 1).collect()}
    if len(sizes) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages")
    if not sizes:
        return {}
    draw = F.pmod(F.xxhash64(F.lit("dictionary"), "doc_id"), F.lit(1_000_000)) / 1_000_000
    rate = F.element_at(F.create_map(*[F.lit(x) for lang, n in sizes.items() for x in (lang, min(1.0, rows / n))]), F.col("lang"))
    blocks = F.greatest(F.ceil(F.length("text") / PIECE_CHARS), F.lit(1))
    begin = F.pmod(F.xxhash64(F.lit("place"), "doc_id"), blocks)
    pieces = F.array(*[F.when(blocks > k, F.col("text").substr((F.pmod(begin + k, blocks) * PIECE_CHARS + 1).cast("int"), F.lit(PIECE_CHARS))) for k in range(PIECES)])
    sample = labelled.where(draw < rate).withColumn("draw", F.xxhash64(F.lit("order"), "doc_id", "text"))
    chosen = sample.select("lang", "draw", F.posexplode(pieces).alias("turn", "text")).where("text is not null").toPandas()
    out = Known()
    taught: list[int] = []
    for lang in sizes:
        own = chosen[chosen["lang"] == lang].sort_values(["turn", "draw", "text"])
        draws = own["draw"].drop_duplicates().tolist()
        teaching = {d for k, d in enumerate(draws) if (k + 1) % KEPT_BACK}
        kept, size = {}, 0
        for text, drawn in zip(own["text"], own["draw"], strict=True):
            text = plain(text.encode())
            if size < DICTIONARY_BYTES and text and text not in kept and drawn in teaching:
                kept[text] = None
                size += len(text)
                taught.append(int(drawn))
        if kept:
            out[lang] = b" ".join(kept)[-DICTIONARY_BYTES:]
    out.calibrate(sample.where(~F.col("draw").isin(*set(taught))) if taught else sample)
    return out


class Known(dict):
    """Dictionaries by language, with the usual margins (binary logarithm of the size, margin)."""

    usual: tuple[tuple[float, float], ...] = ()

    def calibrate(self, rows: DataFrame) -> None:
        """Take the usual margins from ``rows`` (text, lang): medians over texts of like size that were told rightly."""
        if len(self) < 2:
            return
        known = dict(self)

        def measure(batches: Iterable[pa.RecordBatch]):
            sizer = Sizer(known)
            for batch in batches:
                found = []
                for raw, lang in zip(as_bytes(batch.column(0)).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    if told(raw):
                        best, least, lead = margin(sizer.sizes(plain(raw)), sizer.languages)
                        if best == lang:
                            found.append((float(least), lead))
                least, lead = zip(*found, strict=True) if found else ((), ())
                yield pa.RecordBatch.from_arrays([pa.array(least, pa.float64()), pa.array(lead, pa.float64())], ["size", "lead"])

        seen = sorted((r["size"], r["lead"]) for r in arrow_map(rows.select("text", "lang"), measure, "size double, lead double").collect())
        parts = max(1, min(8, len(seen) // ENOUGH))
        groups = [seen[k * len(seen) // parts : (k + 1) * len(seen) // parts] for k in range(parts)] if seen else []
        self.usual = tuple((float(np.log2(np.median([x for x, _ in g]))), float(np.median([x for _, x in g]))) for g in groups)


def told(text: bytes) -> bool:
    """Whether there is a letter to tell a language from."""
    return LETTER.search(text.decode("utf-8", "replace")) is not None


def margin(sizes: list[int], languages: list[str]) -> tuple[str, int, float]:
    """The language of fewest bytes (the first by name of equal ones), these bytes, and the next one's lead over them."""
    best = min(range(len(sizes)), key=sizes.__getitem__)
    least = max(1, sizes[best])
    rivals = [n for k, n in enumerate(sizes) if k != best]
    return languages[best], least, (min(rivals) - sizes[best]) / least if rivals else float("inf")


class Sizer:
    """The compressed size of a text under each language's dictionary."""

    def __init__(self, dictionaries: dict[str, bytes]):
        self.languages = sorted(dictionaries)
        parameters = zstandard.ZstdCompressionParameters.from_level(LEVEL, dict_size=DICTIONARY_BYTES, **SEARCH, write_content_size=False, write_checksum=False, write_dict_id=False)
        self.compressors, self.samples, self.alone = [], [], []
        for lang in self.languages:
            whole = dictionaries[lang]
            cut = min(SAMPLE_BYTES, len(whole) // 2)
            data = zstandard.ZstdCompressionDict(whole[cut:] or b" ", dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            data.precompute_compress(compression_params=parameters)
            self.compressors.append(zstandard.ZstdCompressor(dict_data=data, compression_params=parameters))
            self.samples.append(whole[:cut])
            self.alone.append(len(self.compressors[-1].compress(whole[:cut])))

    def sizes(self, text: bytes) -> list[int]:
        if len(text) < SHORT:
            return [len(c.compress(sample + text)) - alone for c, sample, alone in zip(self.compressors, self.samples, self.alone, strict=True)]
        return [len(c.compress(text)) for c in self.compressors]


def decide(sizes: list[int], languages: list[str], usual: tuple[tuple[float, float], ...] = ()) -> tuple[str, float]:
    """The language of fewest bytes and how sure that is, from 0 to 1: its relative margin against the usual one."""
    best, least, lead = margin(sizes, languages)
    if lead == float("inf"):
        return best, 1.0
    wide = LEAST_PART * (float(np.interp(np.log2(least), *zip(*usual, strict=True))) if usual else USUAL)
    return best, lead / (lead + wide) if lead + wide > 0 else 0.0


def identify(df: DataFrame, dictionaries: dict[str, bytes], text: str = "text", narrow: float = NARROW, prefix: str = "") -> DataFrame:
    """All rows and columns of ``df`` with lang_pred, score and rejected.

    ``und``, with score 0 and rejected, for null, for texts without a letter and if nothing was learned. A score of at
    most ``narrow`` rejects too, but lang_pred still names the best language.
    """
    added = [f"{prefix}{n}" for n in ("lang_pred", "score", "rejected")]
    df = making_room(df, added)
    at = df.columns.index(text)
    names = [*df.columns, *added]
    usual = getattr(dictionaries, "usual", ())

    def rows(batches: Iterable[pa.RecordBatch]):
        sizer = Sizer(dictionaries) if dictionaries else None
        for batch in batches:
            out = []
            for raw in as_bytes(batch.column(at)).to_pylist():
                if sizer is None or not told(raw):
                    out.append((UNKNOWN, 0.0, True))
                    continue
                body = plain(raw)
                lang, score = decide(sizer.sizes(body), sizer.languages, usual)
                out.append((lang, score, score <= narrow))
            lang, score, rejected = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(rejected, pa.bool_())], names)

    fields = [f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields] + [f"`{n}` {k}" for n, k in zip(added, ("string", "double", "boolean"), strict=True)]
    return arrow_map(df, rows, ", ".join(fields))


def held_out(key: str = "doc_id") -> Column:
    return F.pmod(crc_text(F.col(key)), F.lit(4)) == 2


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    known = learn(docs.where(~held_out()))
    return identify(docs.select("doc_id", held_out().alias("held_out"), "text"), known).drop("text")


def known_language(docs: DataFrame, labelled: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose language is not rejected, with its columns."""
    return identify(docs, learn(labelled), prefix="__l_").where("not __l_rejected").select(*docs.columns)
