"""Tables read as collections of images: (image_id, split, payload) and the payload's kind."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from splitguard.operators.raster import grid_raster, with_split


@dataclass(frozen=True)
class Collection:
    images: DataFrame
    kind: str


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _plain(df: DataFrame, key, payload, kind: str) -> Collection:
    slim = df.select(key.cast("long").alias("image_id"), payload.alias("payload"))
    return Collection(with_split(slim).select("image_id", "split", "payload"), kind)


def collection(spark: SparkSession, sf_dir: str, name: str) -> Collection:
    """One of embeddings, documents, pages, part, bigram, activity, ledger, conversations, benchmark."""
    col = F.col
    if name == "embeddings":
        return _plain(table(spark, sf_dir, name), col("vec_id"), col("embedding"), "vector")
    if name == "documents":
        return _plain(table(spark, sf_dir, name), col("doc_id"), col("text"), "text")
    if name == "bigram":
        return _plain(table(spark, sf_dir, "documents"), col("doc_id"), col("text"), "bigram")
    if name == "pages":
        return _plain(table(spark, sf_dir, name), col("page_id"), col("html"), "text")
    if name == "part":
        text = F.concat_ws("|", "p_name", "p_type")
        return _plain(table(spark, sf_dir, name), col("p_partkey"), text, "text")
    if name == "conversations":
        key = col("conv_id") * 1000 + col("turn")
        return _plain(table(spark, sf_dir, name), key, col("text"), "text")
    if name == "benchmark":
        return _plain(table(spark, sf_dir, name), col("item_id"), col("text"), "text")
    if name == "activity":
        events = table(spark, sf_dir, "events")
        grid = grid_raster(events, "user_id", F.dayofmonth("ts") - 1, F.hour("ts"), F.lit(1))
        return Collection(grid, "pixels")
    if name == "ledger":
        lines = table(spark, sf_dir, "lineitem")
        grid = grid_raster(
            lines, "l_suppkey", F.month("l_shipdate") - 1, F.dayofmonth("l_shipdate") - 1, F.col("l_quantity")
        )
        return Collection(grid, "pixels")
    raise ValueError(f"no collection {name}")
