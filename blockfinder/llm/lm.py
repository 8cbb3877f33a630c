"""Language-model scores by class n-grams: exchange clustering, class transitions and word emissions.

The counts of all words and of all neighbours cover the whole training part. Exchange clustering moves units between
classes while the likelihood of the training part grows: the most frequent words, one unit for each ending of all other
words, and one for the end of a text. Then each word of the head, up to ``HEAD`` of them, is moved by itself, by counts of
the classes next to it that Spark adds up; only words beyond the head, which are rare, stay with their ending's class.
A word's probability after the class of the word before it is

    (count + 1/2) * (MIX * P(class | class before) / D(class) + (1 - MIX) / D)

where D is the training mass with 1/2 for each known word and for one unknown word, of the class or of all words.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import arrow_map, ascii_words, crc_text, documents, durable, frequent

HEAD = 1 << 18  # most words whose counts go to each task; all others are joined
HEAD_BYTES = 64  # longer words are never among them
UNITS = 1024
OWN_UNITS = 768
END = UNITS - 1
ENDINGS = END - OWN_UNITS
CLASSES = 64
SWEEPS = 12
HEAD_SWEEPS = 1
MIX = 0.95
PRIOR = 20.0
SLICE = 4 << 20  # bytes of text that a worker takes at once; arrays of its words take many times that


def held_out(key: str = "doc_id") -> Column:
    return F.pmod(crc_text(F.col(key)), F.lit(5)) == 1


def word_counts(df: DataFrame, text: str, train: Column) -> DataFrame:
    """(word, n, n_train) of all words, lower-cased."""

    def rows(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            counts, words = ascii_words(batch.column(0), lower=True)
            coded = words.dictionary_encode()
            codes, size = coded.indices.to_numpy(), len(coded.dictionary)
            own = np.repeat(batch.column(1).to_numpy(zero_copy_only=False), counts)
            if size:
                yield pa.RecordBatch.from_arrays([coded.dictionary.cast(pa.string()), pa.array(np.bincount(codes, minlength=size)), pa.array(np.bincount(codes[own], minlength=size))], ["word", "n", "n_train"])

    partial = arrow_map(df.select(F.col(text).alias("text"), train.alias("train")), rows, "word string, n long, n_train long", SLICE)
    return partial.groupBy("word").agg(F.sum("n").alias("n"), F.sum("n_train").alias("n_train"))


def head_words(counts: DataFrame, most: int = HEAD) -> tuple[list[str], np.ndarray]:
    """The most frequent training words, at most ``most``, with their counts, by descending frequency."""
    known = counts.where("n_train > 0").select("word", "n_train")
    chosen = frequent(known, "word", "n_train", most, HEAD_BYTES)
    if chosen is None:
        return [], np.zeros(0, "i8")
    table = known.where(chosen).toArrow().sort_by([("n_train", "descending"), ("word", "ascending")])
    return table["word"].to_pylist(), table["n_train"].to_numpy()


def endings(words: pa.Array) -> np.ndarray:
    """A hash of each word's last three bytes, below ``ENDINGS``."""
    words = words.cast(pa.large_binary())
    offsets = np.frombuffer(words.buffers()[1], "i8")[words.offset : words.offset + len(words) + 1]
    data = np.frombuffer(words.buffers()[2] or b"\0", np.uint8)
    out = np.zeros(len(words), "i8")
    for k in range(1, 4):
        at = offsets[1:] - k
        out = out * 131 + np.where(at >= offsets[:-1], data[np.maximum(at, 0)].astype("i8") + 1, 0) if len(words) else out
    return out % 1_000_003 % ENDINGS


def units_of(words: pa.Array, head: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Each word's unit, and its place in ``head`` or -1."""
    place = pc.fill_null(pc.index_in(words.cast(pa.large_string()), value_set=head), -1).to_numpy()
    return np.where((place >= 0) & (place < OWN_UNITS), place, OWN_UNITS + endings(words)), place


def with_ends(counts: np.ndarray, units: np.ndarray, end: int = END) -> np.ndarray:
    """The units (or classes) of all texts in a row, each text followed by the end."""
    ends = np.cumsum(counts + 1) - 1
    out = np.full(len(units) + len(counts), end, "i8")
    inside = np.ones(len(out), bool)
    inside[ends] = False
    out[inside] = units
    return out


def unit_pairs(df: DataFrame, text: str, head: pa.Array) -> np.ndarray:
    """How often each unit follows each, over all texts; the start of a text counts as an end before it."""

    def rows(batches: Iterable[pa.RecordBatch]):
        total = np.zeros(UNITS * UNITS, "i8")
        for batch in batches:
            counts, words = ascii_words(batch.column(0), lower=True)
            now = with_ends(counts, units_of(words, head)[0])
            total += np.bincount(np.r_[END, now[:-1]] * UNITS + now, minlength=UNITS * UNITS)
        cells = np.flatnonzero(total)
        for at in range(0, len(cells), 65_536):
            part = cells[at : at + 65_536]
            yield pa.RecordBatch.from_arrays([pa.array(part.astype("i4")), pa.array(total[part])], ["cell", "n"])

    cells = arrow_map(df.select(text), rows, "cell int, n long", SLICE).groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(UNITS * UNITS, "i8")
    out[cells["cell"].to_numpy()] = cells["n"].to_numpy()
    return out.reshape(UNITS, UNITS)


def classes_of(words: pa.Array, head: pa.Array, of_head: np.ndarray, of_unit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each word's class, and its place in ``head`` or -1: words of the head have their own, all others their ending's."""
    place = pc.fill_null(pc.index_in(words.cast(pa.large_string()), value_set=head), -1).to_numpy()
    tied = of_unit[OWN_UNITS + endings(words)]
    return (np.where(place >= 0, of_head[np.maximum(place, 0)], tied) if len(of_head) else tied), place


def neighbour_classes(df: DataFrame, text: str, head: pa.Array, of_head: np.ndarray, of_unit: np.ndarray, smooth: np.ndarray, size: np.ndarray) -> DataFrame:
    """(place, class): the class where the occurrences of each word of the head beyond the core are likeliest, all else as it is.

    Counts of the classes before and behind each word are added up over all texts, as cells that occur.
    """

    def cells(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            counts, words = ascii_words(batch.column(0), lower=True)
            own, place = classes_of(words, head, of_head, of_unit)
            now = with_ends(counts, own, CLASSES - 1)
            word = with_ends(counts, place, -1)
            at = np.flatnonzero(word >= OWN_UNITS)
            if len(at):
                word = word[at]
                before, behind = np.r_[CLASSES - 1, now[:-1]][at], now[np.minimum(at + 1, len(now) - 1)]
                cell, n = np.unique(np.r_[word * 2 * CLASSES + before, word * 2 * CLASSES + CLASSES + behind], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(cell), pa.array(n.astype("i8"))], ["cell", "n"])

    word = F.floor(F.col("cell") / (2 * CLASSES)).cast("int").alias("place")
    counted = arrow_map(df.select(text), cells, "cell long, n long", SLICE).groupBy("cell").agg(F.sum("n").alias("n"))
    rows = counted.groupBy(word).agg(F.collect_list(F.struct((F.col("cell") % (2 * CLASSES)).cast("int").alias("slot"), "n")).alias("x")).select("place", F.col("x.slot").alias("slot"), F.col("x.n").alias("n"))

    def choose(batches: Iterable[pa.RecordBatch]):
        steps = np.log(smooth)
        for batch in batches:
            held = np.zeros((batch.num_rows, 2 * CLASSES))
            row = np.repeat(np.arange(batch.num_rows), pc.list_value_length(batch.column(1)).to_numpy())
            held[row, batch.column(1).flatten().to_numpy()] = batch.column(2).flatten().to_numpy()
            left, right = held[:, :CLASSES], held[:, CLASSES:]
            gain = left @ steps + right @ steps.T - left.sum(axis=1)[:, None] * np.log(np.maximum(size, 1))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(gain[:, : CLASSES - 1].argmax(axis=1).astype("i4"))], ["place", "class"])

    return arrow_map(rows, choose, "place int, class int")


def class_counts(df: DataFrame, counts: DataFrame, text: str, head: pa.Array, of_head: np.ndarray, of_unit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """How often each class follows each over all texts, and the distinct training words of each class."""

    def pairs(batches: Iterable[pa.RecordBatch]):
        total = np.zeros(CLASSES * CLASSES, "i8")
        for batch in batches:
            n, words = ascii_words(batch.column(0), lower=True)
            now = with_ends(n, classes_of(words, head, of_head, of_unit)[0], CLASSES - 1)
            total += np.bincount(np.r_[CLASSES - 1, now[:-1]] * CLASSES + now, minlength=len(total))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], ["cell", "n"])

    def kinds(batches: Iterable[pa.RecordBatch]):
        total = np.zeros(CLASSES, "i8")
        for batch in batches:
            total += np.bincount(classes_of(batch.column(0), head, of_head, of_unit)[0], minlength=CLASSES)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(CLASSES)), pa.array(total)], ["cell", "n"])

    out = []
    for found, cells in ((arrow_map(df.select(text), pairs, "cell long, n long", SLICE), CLASSES * CLASSES), (arrow_map(counts.where("n_train > 0").select("word"), kinds, "cell long, n long"), CLASSES)):
        table = np.zeros(cells, "i8")
        for r in found.groupBy("cell").agg(F.sum("n").alias("n")).collect():
            table[r["cell"]] = r["n"]
        out.append(table)
    return out[0].reshape(CLASSES, CLASSES), out[1]


def transitions(grid: np.ndarray) -> np.ndarray:
    """Smoothed probabilities of each class after each."""
    size, total = grid.sum(axis=0), grid.sum()
    share = size / total if total else np.full(CLASSES, 1 / CLASSES)
    return (grid + PRIOR * share + 1e-9) / (grid.sum(axis=1, keepdims=True) + PRIOR + 1e-9 * CLASSES)


def x_log_x(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.maximum(x, 1))


def exchange(pairs: np.ndarray, classes: int = CLASSES, sweeps: int = SWEEPS) -> np.ndarray:
    """The class of each unit. The end (last unit) is a class of its own; the others start dealt by frequency.

    Each step takes one unit out of its class and puts it where the likelihood of the class pairs is largest.
    """
    units = len(pairs)
    freq = pairs.sum(axis=0) + pairs.sum(axis=1)
    order = [u for u in np.argsort(-freq[: units - 1], kind="stable") if freq[u]]
    of = np.zeros(units, "i8")
    of[order] = np.arange(len(order)) % (classes - 1)
    of[units - 1] = classes - 1
    member = np.zeros((units, classes))
    member[np.arange(units), of] = 1
    member[freq == 0] = 0
    before, behind = pairs.T @ member, pairs @ member  # of each unit: counts by the class before and behind it
    grid = member.T @ pairs @ member
    columns = pairs.T.copy()
    for _ in range(sweeps):
        moves = 0
        for u in order:
            own, old = pairs[u, u], of[u]
            left, right = before[u].copy(), behind[u].copy()
            left[old] -= own
            right[old] -= own
            grid[:, old] -= left
            grid[old] -= right
            grid[old, old] -= own
            ins, outs = grid.sum(axis=0) + right, grid.sum(axis=1) + left  # its own pairs count wherever it goes
            gain = (x_log_x(grid + right) - x_log_x(grid)).sum(axis=1) + (x_log_x(grid + left[:, None]) - x_log_x(grid)).sum(axis=0)
            corner = np.diagonal(grid)
            gain += x_log_x(corner + left + right + own) - x_log_x(corner + left) - x_log_x(corner + right) + x_log_x(corner)
            n_in, n_out = left.sum() + own, right.sum() + own
            gain -= x_log_x(ins + n_in) - x_log_x(ins) + x_log_x(outs + n_out) - x_log_x(outs)
            gain[classes - 1] = -np.inf
            new = int(gain.argmax())
            if gain[new] <= gain[old] + 1e-9 * abs(gain[old]):
                new = old
            grid[:, new] += left
            grid[new] += right
            grid[new, new] += own
            if new != old:
                moves += 1
                of[u] = new
                before[:, old] -= pairs[u]
                before[:, new] += pairs[u]
                behind[:, old] -= columns[u]
                behind[:, new] += columns[u]
        if not moves:
            break
    return of


@dataclass
class Model:
    head: pa.Array
    head_counts: np.ndarray
    of_head: np.ndarray  # class of each word of the head
    of_unit: np.ndarray  # class of each unit; other words have that of their ending
    factor: np.ndarray  # log10 of what (count + 1/2) is multiplied by, for each class before and class
    total: int  # training tokens
    distinct: int  # distinct training tokens
    ends: int  # training texts

    @property
    def mass(self) -> float:
        return self.total + 0.5 * (self.distinct + 1)


def learn(df: DataFrame, counts: DataFrame, text: str, train: Column, sweeps: int = HEAD_SWEEPS) -> Model:
    """From all training texts; the driver sees the head's words and tables of units and classes only.

    Exchange clustering places the core and the endings first. Then each further word of the head goes where it is
    likeliest, all at once against the counts that stand, ``sweeps`` times.
    """
    own = df.where(train)
    words, head_counts = head_words(counts)
    head = pa.array(words, pa.large_string())
    of = exchange(unit_pairs(own, text, head))
    of_head = of[units_of(head, head)[0]] if len(words) else np.zeros(0, "i8")
    grid, kinds = class_counts(own, counts, text, head, of_head, of)
    for _ in range(sweeps if len(words) > OWN_UNITS else 0):
        moved = neighbour_classes(own, text, head, of_head, of, transitions(grid), grid.sum(axis=0)).toArrow()
        of_head[moved["place"].to_numpy()] = moved["class"].to_numpy()
        grid, kinds = class_counts(own, counts, text, head, of_head, of)
    size, total, ends = grid.sum(axis=0), int(grid.sum()), int(grid[:, CLASSES - 1].sum())
    kinds[CLASSES - 1] = int(ends > 0)
    model = Model(head, head_counts, of_head, of, np.zeros((CLASSES, CLASSES)), total, int(kinds.sum()), ends)
    model.factor = np.log10(MIX * transitions(grid) / (size + 0.5 * (kinds + 1)) + (1 - MIX) / model.mass)
    return model


def score(df: DataFrame, counts: DataFrame, model: Model, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_tokens, n_known, base_score, score, perplexity) of every row; null counts as an empty text.

    Words of the head are scored in place; for all others, each row sends its distinct ones to their counts and sums up
    what comes back. Rows that agree in key and text are scored as one and then repeated.
    """
    head, of_head, of_unit, factor, end_class = model.head, model.of_head, model.of_unit, model.factor, CLASSES - 1
    logs, known = np.log10(model.head_counts + 0.5), model.head_counts > 0
    end_log, end_known = float(np.log10(model.ends + 0.5)), int(model.ends > 0)
    kind = df.schema[key].dataType.simpleString()

    def rows(batches: Iterable[pa.RecordBatch]):
        for batch in batches:
            n = batch.num_rows
            counts, words = ascii_words(batch.column(2), lower=True)
            classes, place = classes_of(words, head, of_head, of_unit)
            doc = np.repeat(np.arange(n), counts)
            now = with_ends(counts, classes, end_class)
            steps = factor[np.r_[end_class, now[:-1]], now]
            steps = np.bincount(np.repeat(np.arange(n), counts + 1), steps, n)
            inside = place >= 0
            there = np.where(inside, place, 0)
            own = np.bincount(doc[inside], logs[place[inside]], n) if len(logs) else np.zeros(n)
            seen = np.bincount(doc, inside & known[there], n).astype("i8") if len(logs) else np.zeros(n, "i8")
            # Distinct words outside the head: the row they are in, the word, and how often it is there.
            rare = words.filter(pa.array(~inside)).dictionary_encode()
            pair, times = np.unique(doc[~inside] * max(1, len(rare.dictionary)) + rare.indices.to_numpy(), return_counts=True)
            row, word = np.divmod(pair, max(1, len(rare.dictionary)))
            take = pa.array(np.r_[np.arange(n), row])
            alone = pa.array([f" {h}" for h in batch.column(1).to_pylist()], pa.large_string())  # no word has a space
            none = np.zeros(len(row))
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0).take(take),
                    batch.column(1).take(take),
                    pa.concat_arrays([alone, rare.dictionary.take(pa.array(word))]).cast(pa.string()),
                    pa.array(np.r_[counts + 1, times].astype("i8")),
                    pa.array(np.r_[seen + end_known, none.astype("i8")]),
                    pa.array(np.r_[own + end_log, none]),
                    pa.array(np.r_[steps, none]),
                ],
                ["key", "print", "word", "n", "known", "own", "steps"],
            )

    narrow = df.select(F.col(key).alias("key"), F.xxhash64(F.coalesce(F.col(text), F.lit("")), F.length(text)).alias("print"), F.col(text).alias("text"))
    parts = arrow_map(narrow, rows, f"key {kind}, print long, word string, n long, known long, own double, steps double", SLICE)
    counted = parts.join(counts.select("word", F.col("n_train").alias("c")), "word", "left")
    whole = F.col("word").startswith(" ")
    c = F.coalesce("c", F.lit(0))
    sums = counted.select(
        "key",
        "print",
        F.when(whole, F.lit(1)).otherwise(0).alias("rows"),
        F.when(whole, F.col("n")).otherwise(0).alias("n_tokens"),
        F.when(whole, F.col("known")).when(c > 0, F.col("n")).otherwise(0).alias("n_known"),
        F.when(whole, F.col("own")).otherwise(F.col("n") * F.log10(c + 0.5)).alias("own"),
        F.col("steps"),
    )
    names = ["rows", "n_tokens", "n_known", "own", "steps"]
    one = sums.groupBy("key", "print").agg(*[F.sum(x).alias(x) for x in names]).withColumn("copy", F.explode(F.array_repeat(F.lit(0), F.col("rows").cast("int"))))
    n, own = (F.col("n_tokens") / F.col("rows")).cast("long"), F.col("own") / F.col("rows")
    base, model_score = own - n * F.lit(float(np.log10(model.mass))), own + F.col("steps") / F.col("rows")
    return one.select(F.col("key").alias(key), n.alias("n_tokens"), (F.col("n_known") / F.col("rows")).cast("long").alias("n_known"), base.alias("base_score"), model_score.alias("score"), F.pow(F.lit(10.0), -model_score / n).alias("perplexity"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    counts = durable(word_counts(docs, "text", ~held_out()))
    model = learn(docs, counts, "text", ~held_out())
    scored = score(docs, counts, model)
    return scored.select("doc_id", held_out().alias("held_out"), "n_tokens", "n_known", F.lit(model.total).cast("long").alias("train_tokens"), "base_score", "score", "perplexity")
