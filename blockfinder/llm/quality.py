"""Quality rules and a classifier: hashed word and character n-grams, logistic regression, calibrated probability.

The classifier learns from a bounded sample of labelled rows (``SAMPLE_ROWS``, the first by a hash of the id); all
documents are then scored in Arrow batches against fixed thresholds.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, as_bytes, ascii_words, documents, making_room

BITS = 18
SAMPLE_ROWS = 1800  # labelled rows that are learned from, two thirds for the weights and one for the calibration
CHAR_N = (3, 5)
SLICE = 4 << 20
KEEP_FROM = 0.5  # least calibrated probability of good quality
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
SPACE = np.isin(np.arange(256), [0x20, *range(0x09, 0x0E)])
SYMBOL = np.isin(np.arange(256), list(b"#*$%&|<>"))


@dataclass
class Slice:
    """Texts of one batch laid out for whole-array work: their bytes, each after a line break, and their words."""

    texts: list[bytes]
    data: np.ndarray
    starts: np.ndarray  # of each text in data
    sizes: np.ndarray
    n_words: np.ndarray
    codes: np.ndarray  # of all words, in order
    distinct: list[str]

    @classmethod
    def of(cls, column: pa.Array) -> Slice:
        texts = as_bytes(column).to_pylist()
        data = np.frombuffer(b"\n" + b"\n".join(texts) + b"\n", np.uint8)
        sizes = np.fromiter(map(len, texts), "i8", len(texts))
        counts, words = ascii_words(column, lower=False)
        coded = words.dictionary_encode()
        return cls(texts, data, np.cumsum(sizes + 1) - sizes, sizes, counts, coded.indices.to_numpy(), coded.dictionary.to_pylist())

    def per_text(self, flags: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(flags)])
        return total[self.starts + self.sizes] - total[self.starts]

    def families(self):
        """For each family of n-grams: the hashed feature at each place, and where each text's places start and end."""
        mask = np.uint32((1 << BITS) - 1)
        data = self.data.astype(np.uint32)
        for n in CHAR_N:
            h = np.zeros(max(0, len(data) - n + 1), np.uint32)
            for k in range(n):
                h = h * np.uint32(0x01000193) + data[k : k + len(h)]
            h = (h ^ (h >> np.uint32(15))) * np.uint32(0x85EBCA6B)
            first = np.minimum(self.starts, len(h))
            yield (h >> np.uint32(8)) & mask, first, first + np.maximum(0, self.sizes - n + 1)
        own = np.fromiter((zlib.crc32(w.encode()) for w in self.distinct), np.uint32, len(self.distinct))[self.codes] if len(self.codes) else np.zeros(0, np.uint32)
        ends = np.cumsum(self.n_words)
        yield (own * np.uint32(0x9E3779B1) >> np.uint32(7)) & mask, ends - self.n_words, ends
        both = own[:-1] * np.uint32(0x85EBCA6B) + own[1:] * np.uint32(0xC2B2AE35)
        # A word after itself is one feature, whichever word it is.
        first = np.minimum(ends - self.n_words, len(both))
        yield np.where(own[:-1] == own[1:], np.uint32(0), (both >> np.uint32(9)) & mask), first, first + np.maximum(0, self.n_words - 1)


def sparse(part: Slice) -> list[tuple[np.ndarray, np.ndarray]]:
    """Each text's features: distinct ones and their weight, the mean over the places of each family."""
    found: list[list] = [[] for _ in part.texts]
    for h, a, b in part.families():
        for row, (x, y) in enumerate(zip(a.tolist(), b.tolist(), strict=True)):
            if y > x:
                found[row].append((h[x:y], np.full(y - x, 1 / (y - x))))
    out = []
    for parts in found:
        if not parts:
            out.append((np.zeros(0, "i4"), np.zeros(0, "f4")))
            continue
        index, where = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
        out.append((index.astype("i4"), np.bincount(where, np.concatenate([p[1] for p in parts])).astype("f4")))
    return out


def scores(part: Slice, weights: np.ndarray) -> np.ndarray:
    """The sum over families of each text's mean weight. A text is summed by itself, so that equal ones agree to the last bit."""
    total = np.zeros(len(part.texts))
    for h, a, b in part.families():
        full = b > a
        if full.any():
            bounds = np.column_stack([a[full], b[full]]).ravel()
            total[full] += np.add.reduceat(np.append(weights[h].astype("f8"), 0.0), bounds)[::2] / (b - a)[full]
    return total


def repeat_words(codes: np.ndarray) -> int:
    """Words that lie in a window of three which is found twice or more."""
    if len(codes) < 4:
        return 0
    codes = codes.astype("i8")
    n = int(codes.max()) + 1
    pairs = codes[:-2] * n + codes[1:-1]
    if n > 1 << 20:
        pairs = np.unique(pairs, return_inverse=True)[1]
    _, where, times = np.unique(pairs * n + codes[2:], return_inverse=True, return_counts=True)
    again = times[where] > 1
    covered = np.zeros(len(codes), bool)
    for k in range(3):
        covered[k : k + len(again)] |= again
    return int(covered.sum())


def dup_lines(text: bytes) -> int:
    lines = [x for x in text.split(b"\n") if x and not x.isspace()]
    return len(lines) - len(set(lines))


@dataclass
class Model:
    weights: np.ndarray
    bias: float
    slope: float
    shift: float

    def probability(self, score: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * (score + self.bias) + self.shift, -30, 30)))


def fit_logistic(rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, steps: int = 40, rate: float = 1.0, decay: float = 1e-6) -> tuple[np.ndarray, float]:
    """Logistic regression by full-batch steps with adapted rates; classes weigh alike."""
    sizes = np.array([len(i) for i, _ in rows])
    index, value, row = np.concatenate([i for i, _ in rows]), np.concatenate([v for _, v in rows]).astype("f8"), np.repeat(np.arange(len(rows)), sizes)
    used, index = np.unique(index, return_inverse=True)
    share = np.where(labels == 1, 0.5 / max(1, (labels == 1).sum()), 0.5 / max(1, (labels == 0).sum()))
    w, bias = np.zeros(len(used)), 0.0
    m, v, mb, vb = np.zeros_like(w), np.zeros_like(w), 0.0, 0.0
    for t in range(1, steps + 1):
        z = np.bincount(row, value * w[index], len(rows)) + bias
        g = share * (1 / (1 + np.exp(-np.clip(z, -30, 30))) - labels)
        grad, gb = np.bincount(index, value * g[row], len(w)) + decay * w, g.sum()
        m, v, mb, vb = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2, 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb**2
        one, two = 1 - 0.9**t, 1 - 0.99**t
        w -= rate * (m / one) / (np.sqrt(v / two) + 1e-9)
        bias -= 0.1 * (mb / one) / (np.sqrt(vb / two) + 1e-9)
    weights = np.zeros(1 << BITS, "f4")
    weights[used] = w
    return weights, bias


def calibrate(score: np.ndarray, labels: np.ndarray, steps: int = 200) -> tuple[float, float]:
    """Slope and shift that turn scores into probabilities, by Newton steps with smoothed targets."""
    good, bad = (labels == 1).sum(), (labels == 0).sum()
    scale = max(1e-9, float(np.std(score)))
    x, target = score / scale, np.where(labels == 1, (good + 1) / (good + 2), 1 / (bad + 2))
    a, b = 1.0, 0.0
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a * x + b, -30, 30)))
        d, h = p - target, np.maximum(p * (1 - p), 1e-6)
        ga, gb = (d * x).sum() + 1e-3 * (a - 1), d.sum()
        haa, hab, hbb = (h * x * x).sum() + 1e-3, (h * x).sum(), h.sum() + 1e-9
        det = haa * hbb - hab * hab
        if det <= 1e-12:
            break
        a, b = a - (hbb * ga - hab * gb) / det, b - (haa * gb - hab * ga) / det
        a, b = float(np.clip(a, 0, 100)), float(np.clip(b, -100, 100))
    return a / scale, b


def train(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS) -> Model | None:
    """Learn good (1) from poor (0) quality. None if the sample lacks one of the two.

    ``labels``: doc_id, quality; rows without either are left out, and of several labels of a document the lowest counts.
    """
    chosen = labels.where("doc_id is not null and quality in (0, 1)").groupBy("doc_id").agg(F.min("quality").alias("quality")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)

    def featured(batches):
        for batch in batches:
            found = sparse(Slice.of(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([i for i, _ in found], pa.list_(pa.int32())), pa.array([v for _, v in found], pa.list_(pa.float32()))], ["doc_id", "quality", "index", "value"])

    texts = docs.select(F.col("doc_id").cast("long"), "text").join(F.broadcast(chosen.select(F.col("doc_id").cast("long"), F.col("quality").cast("int"))), "doc_id").select("doc_id", "text", "quality")
    table = arrow_map(texts, featured, "doc_id long, quality int, index array<int>, value array<float>", SLICE).toArrow().sort_by("doc_id")
    quality = table["quality"].to_numpy()
    vectors = [(i.values.to_numpy(), v.values.to_numpy()) for i, v in zip(table["index"], table["value"], strict=True)]
    held = np.arange(len(vectors)) % 3 == 2
    if not {0, 1} <= set(quality[~held].tolist()):
        return None
    weights, bias = fit_logistic([x for x, h in zip(vectors, held, strict=True) if not h], quality[~held])
    out = np.array([float((weights[i] * v).sum()) + bias for i, v in vectors])
    sure = held if {0, 1} <= set(quality[held].tolist()) else ~held
    return Model(weights, bias, *calibrate(out[sure], quality[sure]))


VERDICT = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, quality double, kept boolean"


def judge(df: DataFrame, model: Model | None, text: str = "text", keep_from: float = KEEP_FROM, prefix: str = "") -> DataFrame:
    """All rows and columns of ``df`` with the measures of its text (null: no words), base_failed, quality and kept.

    base_failed: under 50 words, or over half of the words in repeated windows of three. kept: not base_failed, and
    the calibrated probability ``quality`` is at least ``keep_from``. Without a model, quality is null and the base
    rules decide. ``prefix`` goes before the names of new columns, so that they can't clash.
    """
    added = [prefix + x.split()[0] for x in VERDICT.split(", ")]
    df = making_room(df, added)
    at, names = df.columns.index(text), [*df.columns, *added]

    def rows(batches):
        for batch in batches:
            part = Slice.of(batch.column(at))
            lead, word = part.data & 0xC0 != 0x80, ~SPACE[part.data]
            bounds = np.cumsum(part.n_words)
            repeats = np.array([repeat_words(part.codes[b - n : b]) for b, n in zip(bounds, part.n_words, strict=True)], "i8")
            failed = (part.n_words < MIN_WORDS) | (100 * repeats > MAX_REPEAT_PERCENT * part.n_words)
            chance = None if model is None else model.probability(scores(part, model.weights))
            kept = ~failed if chance is None else ~failed & (chance >= keep_from)
            dups = np.fromiter(map(dup_lines, part.texts), "i8", len(part.texts))
            new = [part.n_words, part.per_text(lead & word), part.per_text(SYMBOL[part.data]), dups, repeats, failed]
            kinds = [pa.int64()] * 5 + [pa.bool_()]
            columns = [*[pa.array(x, k) for x, k in zip(new, kinds, strict=True)], pa.array(chance, pa.float64()) if chance is not None else pa.nulls(len(failed), pa.float64()), pa.array(kept)]
            yield pa.RecordBatch.from_arrays([*batch.columns, *columns], names)

    fields = [f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields] + [f"`{n}` {x.split()[1]}" for n, x in zip(added, VERDICT.split(", "), strict=True)]
    return arrow_map(df, rows, ", ".join(fields), SLICE)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return judge(docs.select("doc_id", "text"), model).drop("text")


def good_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` that are kept, with its columns."""
    model = train(docs, labels)
    return judge(docs, model, prefix="__q_").where("__q_kept").select(*docs.columns)
