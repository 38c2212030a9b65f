"""From documents to packed sequences: STAGES, and run() over all of them.

A stage takes (spark, docs, sf_dir) and returns a DataFrame; each one's rows are written as Parquet and read
again as the next one's docs. All but the last keep the columns of documents. No SQL can say what the language, near
duplicate and packing stages do, so there is no oracle: tests compare them with plain versions."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from spectrack.llm import language
from spectrack.llm.common import discard, keep_rows, row_key, staged
from spectrack.llm.exact_dedup import exact_dedup
from spectrack.llm.mixing import mixed_texts
from spectrack.llm.packing import pack
from spectrack.llm.simhash import near_duplicates


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that language identification doesn't reject."""
    model = language.fit(docs.filter(~language.held_out("doc_id", 5, 0)))
    return language.identify(docs, model, keep=True)


def exact_once(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each set of equal texts."""
    return keep_rows(docs, exact_dedup(docs).filter("kept").select("row_key").distinct(), row_key())


def near_once(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of linked fingerprints."""
    return keep_rows(docs, near_duplicates(docs).filter("kept").select("row_key").distinct(), row_key())


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The words that the mix takes: whole copies, and parts of the texts it cuts."""
    return mixed_texts(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents' tokens with their places in sequences."""
    return pack(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("language", known_language),
    ("exact duplicates", exact_once),
    ("near duplicates", near_once),
    ("mix", mixed),
    ("pack", packed),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        made = staged(stage(spark, docs, sf_dir), name.replace(" ", "-"))
        discard(docs)  # nothing, where docs is the input
        docs = made
    return STAGES[-1][1](spark, docs, sf_dir)
