"""Registered queries of the fingerprint engine and their SQL twins.

Each family of queries has a module under plans/; this one puts them together.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from splitguard.plans import audits, hashing, images, tables

Query = Callable[[SparkSession, str], DataFrame]


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return audits.sanitize_report(spark, sf_dir, "part")


def entries() -> dict[str, tuple[Query, str | None]]:
    return hashing.entries() | images.entries() | audits.entries() | tables.entries()


def queries() -> dict[str, Query]:
    return {name: query for name, (query, _) in entries().items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in entries().items() if sql is not None}
