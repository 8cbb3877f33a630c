"""The pipeline's near-copy stage against brute force over all pairs of texts."""

import random

import pytest

from blockfinder.llm import shingles


def brute(texts: dict[int, str]) -> dict[int, int]:
    sets = {}
    for k, t in texts.items():
        w = t.lower().split()
        sets[k] = {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()
    up = {k: k for k in texts}

    def top(k):
        while up[k] != k:
            k = up[k]
        return k

    for a in texts:
        for b in texts:
            x, y = sets[a], sets[b]
            if a < b and (x == y or 5 * len(x & y) >= 4 * len(x | y)):
                low, high = sorted((top(a), top(b)))
                up[high] = low
    return {k: top(k) for k in texts}


@pytest.mark.parametrize("seed", [0, 1])
def test_near_copy_stage_against_brute_force(spark, seed):
    import corpus_pipeline

    rnd = random.Random(seed)
    common = " ".join(f"common{i}" for i in range(12))
    texts, k = {}, 0
    for _ in range(25):
        base = [f"w{rnd.randrange(5000)}" for _ in range(rnd.choice((3, 8, 30, 80, 200)))]
        if rnd.random() < 0.5:
            base += common.split()
        for _ in range(rnd.choice((1, 2, 5))):
            words = list(base)
            for _ in range(rnd.randrange(0, 1 + len(words) // 25)):
                words[rnd.randrange(len(words))] = f"x{rnd.randrange(9999)}"
            texts[k], k = " ".join(words), k + 1
            base = words if rnd.random() < 0.5 else base
    texts[k], texts[k + 1] = "", " \n"
    whole = brute(texts)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    assert {r["doc_id"]: r["component_id"] for r in shingles.near_copies(docs).collect()} == whole
    assert sorted(r["doc_id"] for r in corpus_pipeline.one_of_each(spark, docs, "").collect()) == sorted(set(whole.values()))


def test_rows_without_or_with_repeated_ids(spark):
    text = "the cat sat on the mat and the dog sat on the rug"
    rows = [(1, None, "a"), (2, "", "a"), (4, text, "a"), (5, text, "b"), (5, text, "b"), (None, "no id here", "b")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    assert shingles.near_copies(docs).count() == len(rows)
    kept = shingles.one_of_each(docs)
    assert kept.columns == docs.columns and sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 1, 4]
    assert shingles.near_copies(docs.limit(0)).count() == 0


def grown_group(n: int) -> list[tuple[int, str]]:
    """Edits of one text, many of them too far from each other to be near copies."""
    rnd = random.Random(n)
    base, out = [f"w{i}" for i in range(200)], []
    for k in range(n):
        words = list(base)
        for _ in range(rnd.randrange(1, 9)):
            words[rnd.randrange(len(words))] = f"x{rnd.randrange(10**9)}"
        out.append((k, " ".join(words)))
    return out


def test_pairs_under_one_shingle_do_not_grow_with_the_square_of_the_group(spark, monkeypatch):
    pairs = []
    plain = shingles.similar
    monkeypatch.setattr(shingles, "similar", lambda p, *rest: (pairs.append(p.count()), plain(p, *rest))[1])
    rows = grown_group(400)
    found = shingles.near_copies(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r["doc_id"]: r["component_id"] for r in found.collect()} == brute(dict(rows))
    assert pairs[-1] <= 10 * len(rows)


def test_near_copies_meet_over_the_gray_index(spark):
    rows = [(1, " ".join(f"w{i}" for i in range(400))), (2, " ".join(f"w{i}" for i in range(400)) + " last"), (3, "another text that is short")]
    texts = spark.createDataFrame(rows, "node long, text string")
    assert {tuple(r) for r in shingles.indexed(texts).select(*shingles.in_order("a", "b")).collect()} == {(1, 2)}


def test_marks_never_differ_in_more_bits_than_the_sets_in_shingles(spark):
    texts = grown_group(12) + [(12, ""), (13, "a b")]
    found = {r["node"]: r["marks"] for r in shingles.marks(spark.createDataFrame(texts, "node long, text string")).collect()}
    sets = {k: set(shingles.shingles(t.encode()).tolist()) for k, t in texts}
    for a in sets:
        for b in sets:
            assert sum(((x ^ y) & (2**64 - 1)).bit_count() for x, y in zip(found[a], found[b], strict=True)) <= len(sets[a] ^ sets[b])
