"""Texts in none of the learned languages are rejected, whatever their length; dictionaries come from whole texts."""

import random

from pyspark.sql import functions as F

from blockfinder.llm import language


def test_noise_is_rejected_and_languages_stay(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    known = language.learn(docs.where(~language.held_out()))
    assert known.usual and all(lead > 0 for _, lead in known.usual)
    rnd = random.Random(0)
    noise = []
    for k in range(120):
        letters = "abcdefghijklmnopqrstuvwxyz    " if k % 2 else "0123456789abcdef"
        noise.append((k, "".join(rnd.choice(letters) for _ in range(rnd.choice((1000, 10_000))))))
    rejected = language.identify(spark.createDataFrame(noise, "doc_id long, text string"), known).where("rejected").count()
    assert rejected >= 114
    rows = language.identify(docs.where(language.held_out()).where("length(text) > 200"), known).where("not rejected").collect()
    assert len(rows) > 0.9 * docs.where(language.held_out()).where("length(text) > 200").count()
    assert sum(r["lang"] == r["lang_pred"] for r in rows) > 0.97 * len(rows)


def test_dictionaries_take_pieces_of_whole_texts_of_all_ids(spark):
    rows = spark.range(400).select(F.col("id").alias("doc_id"), F.lit("en").alias("lang"), F.concat(F.lpad("id", 4, "a"), F.repeat(F.lit("start "), 1000), F.repeat(F.lit("end "), 2000)).alias("text"))
    assert b"end end" in language.learn(rows)["en"]
