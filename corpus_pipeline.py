"""From raw documents to packed sequences: five stages, each over all that the stage before kept.

Edge cases are those of the operators: rows with null or letterless text go in the first stage; of equal texts the row
with the largest id stays; of each near-duplicate group (five-word runs, Jaccard 0.8 or more, linked in chains) the row
with the least id stays; passages of benchmark items
are cut out, and rows made of them for the most part go; every other row passes unchanged, with all its columns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ruleworld.llm import decontaminate, exact_dedup, language, near, packing
from ruleworld.sources.scratch import settle, table


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language.drop_rejected(docs)


def one_of_equals(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.drop_copies(docs, keep="largest")


def one_of_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near.drop_near(docs)


def no_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, "byte_bpe_50k.json", end_id=1, capacity=2048)


STAGES = [
    ("language_id", known_language),
    ("exact_dedup", one_of_equals),
    ("simhash_near_dedup", one_of_near),
    ("benchmark_decontamination", no_benchmark),
    ("packing", packed),
]

#: Fingerprints, centroids and token ids are beyond SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = settle(stage(spark, docs, sf_dir))
    return docs
