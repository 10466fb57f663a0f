"""The corpus pipeline: documents without toxic ones, repeated lines and near duplicates, mixed to weights, packed into sequences.

A stage is called as stage(spark, docs, sf_dir) with what its predecessor kept, and its result is written and read again for the next one. All but the
last hand on the columns of `documents`. A document that the mix takes n times has n rows; packing packs each of them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tallygrid.llm import common, lines, minhash, mixing, packing, toxicity
from tallygrid.sources.shared import place


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose whole text is predicted toxic go; the classifier learns from labels outside the held-out fold."""
    return toxicity.reject(docs, toxicity.learned(spark, docs, sf_dir))


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that repeat an earlier line, or from ten words on are within one word of one, go, and documents of which nothing is left; n_chars follows the text."""
    return lines.deduplicate(docs, least_words=1, near_words=10)


def dedup_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates stays, the one with the smallest doc_id."""
    return minhash.deduplicate(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are repeated or left out so that sources have their target shares."""
    return mixing.mix(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents with their sequence and place in it."""
    return packing.packed_documents(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", dedup_lines),
    ("minhash_near_dedup", dedup_documents),
    ("source_mixing", mix_sources),
    ("best_fit_packing", pack_sequences),
]

#: SQL can't express the classifier, the signatures or the tokenizer; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`, each written as Parquet to the shared folder and read again."""
    docs = common.table(spark, sf_dir, "documents")
    shared = place(spark, "pipeline")
    for k, (name, stage) in enumerate(STAGES[:-1]):
        stage(spark, docs, sf_dir).write.parquet(f"{shared}/{k}-{name}")
        docs = spark.read.parquet(f"{shared}/{k}-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
