"""A training corpus from ``documents``: poor texts and unsure languages go, one of each near copy stays, personal data is replaced, and what is left is packed."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from blockfinder.llm import language, packing, pii, quality, shingles
from blockfinder.llm.common import written


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.good_documents(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language.known_language(docs, docs)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return shingles.one_of_each(docs)


def no_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pii.without_personal_data(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(packing.pieces(docs, keep_ids=True), store=written)


STAGES = [
    ("quality rules", good_quality),
    ("language", known_language),
    ("near copies", one_of_each),
    ("personal data", no_personal_data),
    ("packing", packed),
]

#: Compression, tokenizers and keyed permutations are not in SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
    return docs
