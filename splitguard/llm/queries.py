"""Registered queries of the corpus operators: thin digests of the operators' outputs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from splitguard.llm import (
    decontam,
    exactdedup,
    htmltext,
    langid,
    licences,
    secrets,
    sentencepieces,
    sharding,
    simhash,
    sql,
    weakquality,
)


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_digests(_table(spark, sf_dir, "documents"))


def op2_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(_table(spark, sf_dir, "documents"))
    return found.select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )


def op3_byte_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.byte_shards(sharding.sized_rows(_table(spark, sf_dir, "documents")))
    return placed.select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("bytes").alias("law"),
        "shard",
        "slot",
        F.lit(None).cast("int").alias("grown_shard"),
    )


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(_table(spark, sf_dir, "documents"))


def op5_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return htmltext.extract(_table(spark, sf_dir, "pages"))


def op6_licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan_licences(_table(spark, sf_dir, "documents"))


def op7_sentencepieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    return sentencepieces.encode_texts(docs, check=True, text_kept=False)


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontam.contamination(
        _table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark")
    )
    return found.drop("items")


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    groups = exactdedup.first_of_repeats(exactdedup.exact_groups(_table(spark, sf_dir, "documents")))
    return groups.select(
        "doc_id",
        exactdedup.plain_id("keep_id").alias("keep_id"),
        F.col("group_size").cast("long").alias("group_size"),
        "kept",
        "text_sha256",
    )


def op10_weak_label_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return weakquality.score_quality(_table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = [
        op1_secret_scan, op2_simhash_near_dedup, op3_byte_shards, op4_language_id, op5_html_text,
        op6_licence_scan, op7_sentencepieces, op8_decontamination, op9_exact_dedup,
        op10_weak_label_quality,
    ]
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    return sql.oracles()
