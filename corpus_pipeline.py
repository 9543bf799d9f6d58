"""From raw documents to packed training sequences: five stages, each written as a table and read again by the next.

1. Language: documents without a recognisable language go; where no document is labelled, those without a letter.
2. Exact copies: of equal texts the row with the smallest identifier stays.
3. Near copies: of linked documents (five-word shingles, similarity of 0.8 or more) the one with the smallest identifier stays.
4. Mixing: documents are repeated or left out by chance so that sources reach their target weights, and shuffled.
5. Packing: token ids of all that is left, in sequences of at most 2048.

Stages 1 to 4 return the columns of documents, the last one a row per packed piece.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from eqdict.llm import exact_dedup, language, mixing, near_dedup, packing
from eqdict.llm.common import drop, staged, workdir
from eqdict.llm.queries import byte_bpe


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language.of_known_language(docs)


def exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_distinct(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dedup.near_distinct(docs, words=5, percent=80)


def source_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed(docs)


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.packed(docs, byte_bpe())


STAGES = [
    ("language_id", language_id),
    ("exact_copies", exact_copies),
    ("near_copies", near_copies),
    ("source_mixing", source_mixing),
    ("best_fit_packing", best_fit_packing),
]

#: SQL cannot express language profiles or tokens; tests/llm holds the pipeline against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, work = spark.read.parquet(f"{sf_dir}/documents.parquet"), workdir(spark, "pipeline")
    for i, (name, stage) in enumerate(STAGES[:-1]):
        docs = staged(stage(spark, docs, sf_dir), f"{work}/{name}")
        if i:  # what the stage before left has been read
            drop(spark, f"{work}/{STAGES[i - 1][0]}")
    return STAGES[-1][1](spark, docs, sf_dir)
