"""Corpus pipeline: five stages, each written as Parquet and read again for the next.

Language identification, exact de-duplication, near-duplicates (SimHash with pigeonhole blocks, and
keys for what lies farther apart, verified on shingle sets: see nearsets), benchmark
decontamination, SentencePiece encoding.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from splitguard.functions.runtime import ensure_checkpoint_dir, passing_checkpoints, remove_folder
from splitguard.llm import decontam, exactdedup, langid, nearsets, sentencepieces


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is recognised; the column lang keeps its given value."""
    return langid.keep_recognised(docs, langid.fit(docs))


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exactdedup.drop_copies(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group whose five-word shingle sets have a similarity of 0.8 or more."""
    return nearsets.keep_one(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any window of a benchmark item."""
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return decontam.clean(docs, benchmark)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with their piece ids; decoding gave back every text."""
    return sentencepieces.encode_texts(docs, check=True)


STAGES = [
    ("language ID", identify_language),
    ("exact dedup", drop_exact_copies),
    ("SimHash near-dedup", drop_near_copies),
    ("benchmark decontamination", decontaminate),
    ("SentencePiece encoding and decoding", encode),
]

#: Compression sizes and piece search can't be written in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; the tables between them go to the shared folder.

    A stage's checkpoints go when it is written, and a table goes when the next one is; the
    last one stays, since the result reads it.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    base = f"{ensure_checkpoint_dir(spark)}/corpus-{uuid.uuid4().hex}"
    for number, (_, stage) in enumerate(STAGES):
        path = f"{base}/{number}"
        with passing_checkpoints(spark, f"{base}/passing-{number}"):
            stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        if number:
            remove_folder(spark, f"{base}/{number - 1}")
    return docs
