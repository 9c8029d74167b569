"""Contiguous shards of balanced bytes from global prefix sums.

Narrow rows (id, size, checksum) are dealt by range of id. Each partition's
total gives its offset by a prefix sum over as many rows as there are
partitions; a running sum inside the partition completes the global prefix sum.
A row goes to the shard whose equal share of all bytes holds the row's midpoint,
so a shard is off its target by less than one row at either end.

Everything is DataFrame expressions. Texts are read once and never shuffled.

Defined results: a null text has no bytes; ties of id are ordered by size,
checksum and reading order; an empty table gives an empty result; null ids come first.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from splitguard.functions.runtime import reliable, shuffle_width

SHARDS = 24
ROW_BYTES = 8


def sized_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    body = F.coalesce(F.col(text_col), F.lit(""))
    return docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        (F.octet_length(body) + ROW_BYTES).cast("long").alias("size"),
        F.crc32(F.encode(body, "UTF-8")).alias("text_crc32"),
    )


def byte_shards(rows: DataFrame, shards: int = SHARDS) -> DataFrame:
    """rows (doc_id, size, text_crc32) with shard and slot, contiguous in doc_id."""
    slim = reliable(rows.withColumn("at", F.monotonically_increasing_id()))
    order = ["doc_id", "size", "text_crc32", "at"]
    width = shuffle_width(rows.sparkSession)
    dealt = reliable(
        slim.repartitionByRange(width, *order).withColumn("part", F.spark_partition_id())
    )

    totals = dealt.groupBy("part").agg(
        F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("n")
    )
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    offsets = totals.select(  # one row a partition
        "part",
        F.coalesce(F.sum("bytes").over(before), F.lit(0)).alias("bytes_before"),
        F.coalesce(F.sum("n").over(before), F.lit(0)).alias("rows_before"),
        F.sum("bytes").over(whole).alias("all_bytes"),
    )
    offsets = reliable(offsets)

    inside = Window.partitionBy("part").orderBy(*order)
    running = dealt.repartitionByRange(width, "part").select(
        "*",
        F.sum("size").over(inside.rowsBetween(Window.unboundedPreceding, 0)).alias("upto"),
        F.row_number().over(inside).alias("nth"),
    )
    placed = running.join(F.broadcast(offsets), "part").select(
        "doc_id",
        "size",
        "text_crc32",
        (F.col("rows_before") + F.col("nth") - 1).alias("row"),
        # Twice the midpoint of the row's bytes, to stay with integers.
        (2 * (F.col("bytes_before") + F.col("upto")) - F.col("size")).alias("mid2"),
        "all_bytes",
    )
    shard = F.least(
        F.lit(shards - 1), F.expr(f"(mid2 * {int(shards)}) div (2 * all_bytes)")
    ).cast("int")
    placed = reliable(placed.select("doc_id", "size", "text_crc32", "row", shard.alias("shard")))
    firsts = placed.groupBy("shard").agg(F.min("row").alias("first"))  # one row a shard
    return placed.join(F.broadcast(firsts), "shard").select(
        "doc_id",
        "size",
        "text_crc32",
        "shard",
        (F.col("row") - F.col("first")).alias("slot"),
    )
