"""Functions and views for SQL: register(spark) once a session."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from splitguard.functions.dct import PAPER_OPS
from splitguard.operators.fingerprint import Hash, hash_rasters
from splitguard.operators.raster import scan_rasters


def _text_hash(spec: Hash):
    def kernel(texts: pd.Series) -> pd.Series:
        return pd.Series(hash_rasters(scan_rasters(pa.array(texts, pa.string())), spec)[:, 0])

    kernel.__annotations__ = {"texts": pd.Series, "return": pd.Series}
    return pandas_udf(kernel, "long")


def _bit_balance():
    def kernel(hashes: pd.Series) -> float:
        """Mean number of set bits."""
        return float(hashes.map(lambda h: (int(h) & (1 << 64) - 1).bit_count()).mean())

    kernel.__annotations__ = {"hashes": pd.Series, "return": float}
    return pandas_udf(kernel, "double")


class Orientations:
    """(op, hash) rows of an array of oriented hashes in the order of the operations."""

    def eval(self, hashes: list):
        for op, value in zip(PAPER_OPS, hashes or []):
            yield op, value


def register(spark: SparkSession) -> None:
    """phash_udf, ahash_udf over texts, bit_balance, orientations, hamming."""
    spark.udf.register("phash_udf", _text_hash(Hash(threshold="mean_ac")))
    spark.udf.register("ahash_udf", _text_hash(Hash(kind="ahash")))
    spark.udf.register("bit_balance", _bit_balance())
    spark.udtf.register("orientations", udtf(Orientations, returnType="op string, hash long"))
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION hamming(a BIGINT, b BIGINT) RETURNS INT RETURN bit_count(a ^ b)"
    )


def register_views(spark: SparkSession, sf_dir: str) -> None:
    """Temporary views of all tables and of the fingerprinted part collection."""
    from splitguard.operators.fingerprint import phash
    from splitguard.sources.carriers import collection, table

    for name in ("documents", "part", "pages", "embeddings", "labels", "lineitem", "orders"):
        table(spark, sf_dir, name).createOrReplaceTempView(f"v_{name}")
    part = collection(spark, sf_dir, "part")
    phash(part.images, part.kind, threshold="mean_ac").createOrReplaceTempView("v_part_hashes")


def leakage_report(spark: SparkSession, sf_dir: str):
    """The nine official cells of part, written in SQL over the registered views.

    A split against itself counts its removable copies.
    """
    register_views(spark, sf_dir)
    return spark.sql(
        """
        WITH by_hash AS (
            SELECT hash, split, count(*) AS n FROM v_part_hashes GROUP BY hash, split
        ), held AS (
            SELECT hash, map_from_entries(collect_list(struct(split, n))) AS sizes FROM by_hash GROUP BY hash
        ), cells AS (
            SELECT s.search, t.target, hash, coalesce(sizes[s.search], 0) AS own, coalesce(sizes[t.target], 0) AS other
            FROM held
            LATERAL VIEW explode(array('train', 'val', 'test')) s AS search
            LATERAL VIEW explode(array('train', 'val', 'test')) t AS target
        )
        SELECT search, target, sum(own) AS n_search,
               coalesce(sum(CASE WHEN hash IS NULL THEN 0 WHEN search = target THEN greatest(own - 1, 0)
                                 WHEN other > 0 THEN own END), 0) AS n_hits
        FROM cells GROUP BY search, target
        """
    ).withColumn("n_hits", F.col("n_hits").cast("long"))
