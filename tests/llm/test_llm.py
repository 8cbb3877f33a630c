"""Each operator against brute force on small rows, and on nulls, empty and long texts, ties, repeats and clashing names."""

import collections
import heapq
import itertools
import math
import random
import struct
import zlib

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from blockfinder.llm import common, components, counting, language, lm, media, packing, pieces, pii, quality, sharding, simhash

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, fp string, score string, shard string, word string"
ODD = [
    (1, None, "en", "a", 0, 1, "x", "y", "z", "w"),
    (2, "", None, "a", 0, 1, "x", "y", "z", "w"),
    (3, " \n\t ", "en", None, 0, 1, "x", "y", "z", "w"),
    (4, "the cat sat on the mat and the dog sat on the rug", "en", "b", 0, 1, "x", "y", "z", "w"),
    (5, "the cat sat on the mat and the dog sat on the rug", "en", "b", 0, 1, "x", "y", "z", "w"),
    (5, "the cat sat on the mat and the dog sat on the rug", "en", "b", 0, 1, "x", "y", "z", "w"),
    (6, "le chat est sur la table " * 4000, "fr", "b", 0, 1, "x", "y", "z", "w"),
    (7, "日本語 テキスト ééé <|endoftext|> 'll", "fr", "b", 0, 1, "x", "y", "z", "w"),
    (None, "no id here", "en", "b", 0, 1, "x", "y", "z", "w"),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark):
    rows = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    return rows


def texts_of(docs):
    return {r["doc_id"]: r["text"] or "" for r in docs.collect()}


def test_longest_first_is_the_heap_schedule():
    rnd = random.Random(2)
    for _ in range(200):
        k, sizes = rnd.randint(1, 6), {rnd.randint(1, 40): rnd.randint(0, 60) for _ in range(rnd.randint(0, 12))}
        loads, heap = [0] * k, [(0, i) for i in range(k)]
        for size, _, n, at in sharding.longest_first(sorted(sizes.items(), reverse=True), k):
            loads[at] += size * n
        for size in sorted(sizes, reverse=True):
            for _ in range(sizes[size]):
                load, i = heapq.heappop(heap)
                heapq.heappush(heap, (load + size, i))
        assert sorted(loads) == sorted(x for x, _ in heap)


def test_shards(spark, docs, odd, empty):
    def run(df):
        text = F.col("text")
        return sharding.shard(df, "doc_id", sharding.text_group(text), F.coalesce(F.octet_length(text), F.lit(0)) + 1, 4).collect()

    rows, text = run(docs), texts_of(docs)
    assert len(rows) == len(text)
    home = collections.defaultdict(set)
    for r in rows:
        home[text[r["doc_id"]]].add(r["shard"])
    assert all(len(s) == 1 for s in home.values())
    for k in range(4):
        assert sorted(r["slot"] for r in rows if r["shard"] == k) == list(range(sum(r["shard"] == k for r in rows)))
    loads = [sum(r["size"] for r in rows if r["shard"] == k) for k in range(4)]
    assert max(loads) - min(loads) <= max(r["size"] for r in rows)
    assert len(run(odd)) == len(ODD) and not run(empty)


def test_schedule_in_parts_is_the_schedule(spark, docs, monkeypatch):
    size = F.coalesce(F.octet_length("text"), F.lit(0)) + 1
    many = docs.unionByName(docs.where("doc_id < 3").select(F.explode(F.sequence(F.lit(10_000), F.lit(10_400))).alias("doc_id"), *docs.columns[1:]))
    found = []
    for at_once, hot in ((500_000, 4096), (7, 10)):
        monkeypatch.setattr(sharding, "AT_ONCE", at_once)
        monkeypatch.setattr(common, "HOT", hot)
        found.append(sorted(map(tuple, sharding.shard(many, "doc_id", sharding.text_group(F.col("text")), size, 5).collect())))
    assert found[0] == found[1] and len(found[0]) == many.count()


@pytest.mark.parametrize("hot", [1, 3, 10**6])
def test_uneven_joins(spark, hot, monkeypatch):
    monkeypatch.setattr(common, "HOT", hot)
    keys = ["a"] * 40 + [None] * 30 + list("bcdefghij") * 2
    rows = spark.createDataFrame(list(enumerate(keys)), "id long, k string")
    home = rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("least"))
    out = common.join_uneven(rows, home, "k", "n", len(keys))
    assert out.columns == ["id", "k", "least"]
    assert sorted((r["id"], r["least"]) for r in out.collect()) == [(i, keys.index(k)) for i, k in enumerate(keys)]
    assert common.join_uneven(rows.limit(0), home.limit(0), "k", "n", 0).count() == 0


def test_lattice_against_brute_force(spark, docs, odd, empty):
    vocabulary = pieces.Pieces.load(pieces.default_path())
    best_of = {t: (i, s) for i, (t, s, n) in enumerate(zip(vocabulary.text, vocabulary.score, vocabulary.normal, strict=True)) if n}

    def brute(word):
        best = [(0.0, [])] + [None] * len(word)
        for stop in range(1, len(word) + 1):
            for start in range(max(0, stop - vocabulary.longest), stop):
                part = word[start:stop]
                if part in best_of:
                    way = (best[start][0] + best_of[part][1], best[start][1] + [best_of[part][0]])
                elif stop - start == 1:
                    way = (best[start][0] + vocabulary.least - pieces.UNKNOWN_COST, best[start][1] + [vocabulary.byte_ids[b] for b in part.encode()])
                else:
                    continue
                if best[stop] is None or way[0] >= best[stop][0]:
                    best[stop] = way
        return best[-1][1]

    few = docs.limit(25).unionByName(odd.where("doc_id <> 6 or doc_id is null").select(*docs.columns))
    rows = pieces.decode(pieces.encode(few)).collect()
    assert len(rows) == 25 + len(ODD) - 1
    for r in rows:
        assert r["ids"] == brute(vocabulary.normalise(r["text"]))
        assert r["decoded"] == (r["text"] or "") and r["n_tokens"] == len(r["ids"])
    assert not pieces.encode(empty).collect()


def test_scores_against_brute_force(spark, docs, odd, empty):
    train = ~lm.held_out()

    def run(df):
        counts = lm.word_counts(df, "text", train).persist()
        model = lm.learn(df, counts, "text", train)
        return model, lm.score(df, counts, model).collect()

    model, rows = run(docs)
    words = {k: [*t.encode().lower().split(), None] for k, t in texts_of(docs).items()}
    count = collections.Counter(w for k, ws in words.items() if zlib.crc32(str(k).encode()) % 5 != 1 for w in ws)
    total, mass = sum(count.values()), math.log10(sum(count.values()) + 0.5 * (len(count) + 1))
    assert model.total == total and len(rows) == len(words)
    gain = 0.0
    for r in rows:
        own = words[r["doc_id"]]
        assert r["base_score"] == pytest.approx(sum(math.log10(count[w] + 0.5) - mass for w in own))
        assert (r["n_tokens"], r["n_known"]) == (len(own), sum(count[w] > 0 for w in own))
        gain += r["score"] - r["base_score"]
    assert gain > 0
    # After each class, all words and one unknown word of each class have a mass of about 1.
    assert (10**model.factor * (model.mass / lm.CLASSES)).min() > 0
    _, rows = run(odd)
    assert len(rows) == len(ODD) and all(r["n_tokens"] == 1 for r in rows if r["doc_id"] in (1, 2, 3))
    assert not run(empty)[1]


def test_held_out_texts_do_not_change_the_model(spark, docs, monkeypatch):
    monkeypatch.setattr(lm, "OWN_UNITS", 40)
    monkeypatch.setattr(lm, "ENDINGS", lm.END - 40)
    train = ~lm.held_out()
    other = docs.withColumn("text", F.when(train, F.col("text")).otherwise(F.repeat(F.lit("zebra quagga okapi "), 300)))
    models = []
    for df in (docs, other):
        counts = lm.word_counts(df, "text", train).persist()
        models.append(lm.learn(df, counts, "text", train))
    one, two = models
    assert one.head.equals(two.head) and len(one.head) > 40
    assert (one.of_head == two.of_head).all() and (one.of_unit == two.of_unit).all() and (one.factor == two.factor).all()


def test_words_of_the_head_go_where_they_are_likeliest(spark, monkeypatch):
    monkeypatch.setattr(lm, "OWN_UNITS", 4)
    monkeypatch.setattr(lm, "ENDINGS", lm.END - 4)
    rng = np.random.default_rng(3)
    nouns, verbs = [f"n{k}x" for k in range(30)], [f"v{k}x" for k in range(30)]
    texts = [" ".join(w for _ in range(20) for w in ("the", str(rng.choice(nouns)), "may", str(rng.choice(verbs)))) for _ in range(80)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    counts = lm.word_counts(df, "text", F.lit(True)).persist()
    plain, moved = (lm.learn(df, counts, "text", F.lit(True), sweeps=k) for k in (0, 2))
    place = {w: k for k, w in enumerate(moved.head.to_pylist())}
    kinds = [{int(moved.of_head[place[w]]) for w in words if w in place and place[w] >= 4} for words in (nouns, verbs)]
    assert not kinds[0] & kinds[1]
    scores = [sum(r["score"] for r in lm.score(df, counts, m).collect()) for m in (plain, moved)]
    assert scores[1] >= scores[0]


def test_exchange_gains_are_exact():
    rng = np.random.default_rng(0)
    pairs = rng.integers(0, 6, (40, 40))
    of = lm.exchange(pairs, 5, 300)

    def likelihood(of):
        m = np.zeros((40, 5))
        m[np.arange(40), of] = 1
        g = m.T @ pairs @ m
        return lm.x_log_x(g).sum() - lm.x_log_x(g.sum(axis=0)).sum() - lm.x_log_x(g.sum(axis=1)).sum()

    best = likelihood(of)
    for u in range(39):
        for c in range(4):
            other = of.copy()
            other[u] = c
            assert likelihood(other) <= best + 1e-6


def test_pseudonyms(spark, odd, empty):
    for v in itertools.product(range(3), range(4), range(5)):
        assert pii.permute(pii.permute(list(v), [3, 4, 5], b"k", "t"), [3, 4, 5], b"k", "t", True) == list(v)
    assert len({tuple(pii.permute(list(v), [3, 4, 5], b"k", "t")) for v in itertools.product(range(3), range(4), range(5))}) == 60
    text = 'Bob.S9@mail.example.com 4111 1111 1111 1111 4111111111111112 2020-02-29 31.06.2020 3/28/1999 10.0.0.1 v1.2.3.4.5 123-45-6789 +1 (386) 555-3733 DE89370400440532013000 token = "9233A8ECF7C5B09FE5949719B6B82BC439E9329B" CC BY-NC 4.0.'
    new, spans = pii.Pseudonyms(b"key").replace(text)
    assert [s[0] for s in spans] == ["email", "card", "date", "date", "address", "social", "phone", "iban", "secret"]
    assert len(new) >= len(text) - 12 and pii.Pseudonyms(b"key", True).replace(new)[0] == text
    assert "4111111111111112" in new and "31.06.2020" in new and "1.2.3.4.5" in new and "4111 1111" not in new
    rows = pii.pseudonymise(spark.createDataFrame([(1, f"a {text}"), (2, f"b {text}"), (3, None), (4, "clean")], "doc_id long, text string"), b"key").collect()
    by = {r["doc_id"]: r for r in rows}
    assert by[1]["text"][2:] == by[2]["text"][2:] == new and by[3]["text"] is None and by[3]["pii_values"] == 0 and by[4]["text"] == "clean"
    out = pii.pseudonymise(odd)
    assert out.columns == [*odd.columns, "pii_values", "pii_spans"] and out.count() == len(ODD) and pii.pseudonymise(empty).count() == 0


def test_language(spark, docs, odd, empty):
    known = language.learn(docs.where(~language.held_out()))
    rows = language.identify(docs.where(language.held_out()), known).where("length(text) > 200").collect()
    assert sum(r["lang"] == r["lang_pred"] for r in rows) >= 0.95 * len(rows) and all(0 <= r["score"] <= 1 for r in rows)
    out = {r["doc_id"]: r["__x_lang_pred"] for r in language.identify(odd, known, prefix="__x_").collect()}
    assert out[1] == out[2] == out[3] == "und" and out[6] == "fr" and out[4] in known
    assert language.identify(empty, known).count() == 0 and language.learn(empty) == {}
    assert {r["lang_pred"] for r in language.identify(odd, {}).collect()} == {"und"}


def brute_fingerprint(text):
    words = [w for w in text.translate({c: c + 32 for c in range(65, 91)}).replace("\x0b", " ").replace("\x0c", " ").replace("\t", " ").replace("\n", " ").replace("\r", " ").split(" ") if w]
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def brute_components(fps):
    keys = list(fps)
    up = {k: k for k in keys}

    def top(k):
        while up[k] != k:
            k = up[k]
        return k

    for a, b in itertools.combinations(keys, 2):
        if (fps[a] ^ fps[b]).bit_count() <= 4:
            x, y = sorted((top(a), top(b)))
            up[y] = x
    return {k: top(k) for k in keys}


def test_near_copies_against_brute_force(spark, docs, odd, empty):
    text = texts_of(docs)
    rnd = random.Random(0)
    for k in range(60):
        words = text[k].split(" ")
        words[rnd.randrange(len(words))] = "changed"
        text[10_000 + k] = " ".join(words)
    fps = {k: brute_fingerprint(t) for k, t in text.items()}
    whole = brute_components(fps)
    rows = simhash.near_copies(spark.createDataFrame(list(text.items()), "doc_id long, text string")).collect()
    assert {r["doc_id"]: r["fp"] % (1 << 64) for r in rows} == fps
    assert {r["doc_id"]: r["component_id"] for r in rows} == whole
    assert simhash.near_copies(odd).count() == len(ODD) and simhash.near_copies(empty).count() == 0
    kept = simhash.one_of_each(odd).collect()
    assert sorted(r["doc_id"] or 0 for r in kept) == [0, 1, 4, 6, 7] and kept[0].asDict().keys() == set(odd.columns)


def test_index_chunks_and_components(spark, monkeypatch):
    rng = np.random.default_rng(1)
    fps = set()
    for base in rng.integers(0, 2**63, 12):
        for _ in range(25):
            x = int(base)
            for bit in rng.integers(0, 64, rng.integers(0, 5)):
                x ^= 1 << int(bit)
            fps.add(x % (1 << 64))
    monkeypatch.setattr(simhash, "CHUNK", 16)
    rows = spark.createDataFrame([(simhash.signed(x),) for x in sorted(fps)], "fp long")
    roots = {r["node"]: r["root"] for r in components.components(simhash.links(rows)).collect()}
    whole = brute_components({simhash.signed(x): x for x in fps})
    found = collections.defaultdict(set)
    for x in whole:
        found[whole[x]].add(roots.get(x, x))
    assert all(len(s) == 1 for s in found.values()) and len({next(iter(s)) for s in found.values()}) == len(found)


@pytest.mark.parametrize("one_task", [0, 200_000])
def test_long_chains_of_links(spark, one_task):
    order = [*range(2500), *np.random.default_rng(0).permutation(np.arange(2500, 5000)).tolist()]
    path = spark.createDataFrame([*itertools.pairwise(order), (9000, 9001), (7, 7), (None, 3)], "a long, b long")
    roots = {r["node"]: r["root"] for r in components.components(path, one_task).collect()}
    assert {roots[k] for k in order} == {0} and roots[9001] == roots[9000] == 9000


def test_near_copies_along_a_chain(spark):
    words = [f"w{k}" for k in range(400)]
    texts = [" ".join(words[k : k + 300]) for k in range(100)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rows = {r["doc_id"]: r for r in simhash.near_copies(df).collect()}
    whole = brute_components({k: r["fp"] % (1 << 64) for k, r in rows.items()})
    assert {k: r["component_id"] for k, r in rows.items()} == {k: min(x for x in whole if whole[x] == whole[k]) for k in rows}


def test_packing(spark, docs, odd, empty):
    from tokenizers import Tokenizer

    rnd = random.Random(1)
    for _ in range(100):
        window = rnd.choice([7, 16, 50])
        sizes = {rnd.randint(1, window): rnd.randint(0, 30) for _ in range(rnd.randint(1, 20))}
        left = []
        for n in sorted(sizes, reverse=True):
            for _ in range(sizes[n]):
                fits = [i for i, r in enumerate(left) if r >= n]
                if fits:
                    left[min(fits, key=lambda i: left[i])] -= n
                else:
                    left.append(window - n)
        placed = packing.best_fit_decreasing(sizes, window)
        fill = collections.Counter()
        for n, count in sizes.items():
            for j in range(count):
                k = max(i for i, (m, r) in enumerate(zip(placed.length, placed.rank, strict=True)) if m == n and r <= j)
                fill[placed.first[k] + (j - placed.rank[k]) // placed.per[k]] += n
        assert sorted(window - f for f in fill.values()) == sorted(left)
    slow = Tokenizer.from_file(packing.default_path())
    both = docs.select("doc_id", "text").unionByName(odd.select("doc_id", "text"))
    rows = packing.pack(packing.pieces(both, keep_ids=True)).collect()
    ids = collections.defaultdict(list)
    for r in sorted(rows, key=lambda r: r["start"]):
        ids[r["doc_id"]].append(r)
        assert r["ids_crc32"] == zlib.crc32(np.array(r["ids"], "<u4").tobytes()) and len(r["ids"]) == r["length"]
    for k, t in texts_of(docs).items():
        if k not in range(1, 8):
            assert [i for r in ids[k] for i in r["ids"]] == [*slow.encode(t, add_special_tokens=False).ids, 1]
    spans = collections.defaultdict(list)
    for r in rows:
        spans[r["sequence_id"]].append((r["offset"], r["length"]))
    for s in spans.values():
        at = 0
        for offset, length in sorted(s):
            assert offset == at
            at += length
        assert at <= 2048
    assert not packing.pack(packing.pieces(empty)).collect()


def test_media(spark, odd, empty):
    for n in (64, 64 * 255, 64 * 256, 64 * 257):
        payload = random.Random(n).randbytes(n)
        data = media.write_container(payload)
        track = media.track_features(data)[0]
        assert media.read_samples(data) == payload and track["codec"] == "raw" and track["samples"] == n // 64 and track["duration"] == n // 64 * 40
        assert [data[a : a + s] for a, s in track["keyframes"]] == [payload[k : k + 64] for k in range(0, n, 64 * 16)]
    for broken in (None, b"", b"x", data[:50], data[: len(data) // 2], struct.pack(">I4s", 4, b"moov") + b"zzz"):
        media.track_features(broken)
    rows = media.text_containers(odd).collect()
    assert len(rows) == len(ODD) and all(r["payload_bytes"] % 64 == 0 and r["payload_bytes"] >= 64 for r in rows)
    by = {r["doc_id"]: r for r in rows}
    assert by[1]["payload_bytes"] == 64 and by[1]["tail_crc32"] == zlib.crc32(bytes(64)) and by[4]["media_sha256"] == by[5]["media_sha256"]
    read = media.media_columns(spark.createDataFrame([(1, bytes(data)), (2, None), (3, b"junk")], "k long, c binary"), "k", "c").collect()
    assert [len(r["tracks"]) for r in sorted(read, key=lambda r: r["key"])] == [1, 0, 0]
    assert media.text_containers(empty).count() == 0


def test_counts_follow_edits(spark, odd, empty):
    import base64

    import public_tokenizers
    import tiktoken

    with open(counting.default_path(), "rb") as file:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, file)}
    slow = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    count, rnd = counting.counter(counting.default_path()), random.Random(3)
    parts = ["a", "b", " ", "  ", "\n", "\n\n", "'", "s", "'s", "12", "é", "!!", "the ", "don't ", "\t", "ll"]
    for _ in range(1500):
        text = "".join(rnd.choice(parts) for _ in range(rnd.choice([0, 1, 5, 60, 400])))
        tree = counting.CountTree(text, count, leaf=rnd.choice([2, 8, 64]))
        for _ in range(4):
            start = rnd.randint(0, len(text) + 2)
            stop, new = start + rnd.choice([0, 0, 1, 3, 20]), "".join(rnd.choice(parts) for _ in range(rnd.choice([0, 1, 3, 30])))
            tree.edit(start, stop, new)
            at = min(start, len(text))
            text = text[:at] + new + text[max(at, min(stop, len(text))) :]
            assert tree.text == text and tree.total == len(slow.encode_ordinary(text))
            assert tree.pre_tokens()[0] == [len(x) for x in counting.PRE_TOKEN.findall(text)]
    rows = counting.apply_edits(counting.build_trees(odd).withColumn("edits", counting.trial_edits())).collect()
    assert len(rows) == len(ODD)
    for r in rows:
        assert r["n_tokens_edited"] == len(slow.encode_ordinary(r["text"])) == sum(r["tokens"])
    long = next(r for r in rows if r["doc_id"] == 6)
    assert long["chars_encoded"] < 300 < long["n_chars_edited"]
    assert counting.build_trees(empty).count() == 0


def brute_quality(text):
    words = [w for w in text.replace("\x0b", " ").replace("\x0c", " ").replace("\t", " ").replace("\n", " ").replace("\r", " ").split(" ") if w]
    windows = collections.Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    covered = {i + k for i in range(len(words) - 2) if windows[tuple(words[i : i + 3])] > 1 for k in range(3)}
    lines = [x for x in text.split("\n") if x.strip(" \t\n\r\x0b\x0c")]
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(covered)


def test_quality(spark, docs, odd, empty):
    big = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    model = quality.train(big, labels)
    rows = quality.judge(big.select("doc_id", "text"), model).collect()
    truth = {r["doc_id"]: r["quality"] for r in labels.collect()}
    clean = [r for r in rows if truth.get(r["doc_id"]) == 1 and not r["base_failed"]]
    poor = [r for r in rows if truth.get(r["doc_id"]) == 0]
    assert sum(r["kept"] for r in clean) >= 0.97 * len(clean) and sum(r["kept"] for r in poor) <= 0.1 * len(poor)
    for r in quality.judge(docs.select("doc_id", "text").unionByName(odd.select("doc_id", "text")), model).collect():
        own = brute_quality(r["text"] or "")
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == own
        assert r["base_failed"] == (own[0] < 50 or 100 * own[4] > 50 * own[0]) and not (r["kept"] and r["base_failed"])
    assert quality.judge(odd, None, prefix="__q_").count() == len(ODD) and quality.judge(empty.select("doc_id", "text"), model).count() == 0
    assert quality.train(big, labels.limit(0)) is None


def test_equal_texts_have_equal_scores():
    rng = np.random.default_rng(4)
    weights = rng.normal(size=1 << quality.BITS)
    text = "some words that stand in several places of a batch, 12 times"
    texts = [" ".join(map(str, rng.integers(0, 999, int(n)))) if n else text for n in rng.integers(0, 40, 300) * rng.integers(0, 2, 300)] + ["", None]
    found = quality.scores(quality.Slice.of(pa.array(texts)), weights)
    assert len({found[k] for k, t in enumerate(texts) if t == text}) == 1 and found[-1] == found[-2] == 0


def test_pipeline(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf).persist()
        assert docs.columns == columns and docs.count() <= seen, name
        seen = docs.count()
    rows = corpus_pipeline.STAGES[-1][1](spark, docs, sf).collect()
    assert {r["doc_id"] for r in rows} == {r["doc_id"] for r in docs.collect()} and len(corpus_pipeline.STAGES) == 5


def test_words_in_slices():
    from blockfinder.llm.common import ascii_words

    texts = pa.array(["É B\x0bc  d\n", None, "", " x\x1cY "] * 50)
    for at in (0, 3, 70):
        part = texts.slice(at, 60)
        for lower in (True, False):
            counts, words = ascii_words(part, lower)
            own = [((t or "").encode().lower() if lower else (t or "").encode()).split() for t in part.to_pylist()]
            assert counts.tolist() == list(map(len, own)) and [w.encode() for w in words.to_pylist()] == [w for o in own for w in o]


def test_class_ngrams_take_texts_in_small_slices(spark, monkeypatch):
    """Arrays of words take many times their text, in each of an executor's workers."""
    from blockfinder.llm import lm

    taken = []
    plain = lm.arrow_map
    monkeypatch.setattr(lm, "arrow_map", lambda df, rows, schema, *most: (taken.append((df.columns, most)), plain(df, rows, schema, *most))[1])
    docs = spark.createDataFrame([(k, f"some words of text {k} and more of them") for k in range(20)], "doc_id long, text string")
    counts = lm.word_counts(docs, "text", ~lm.held_out()).cache()
    lm.score(docs, counts, lm.learn(docs, counts, "text", ~lm.held_out())).count()
    passes = [most for columns, most in taken if "text" in columns]
    assert len(passes) >= 4 and all(most and most[0] <= 4 << 20 for most in passes)
