"""Near matches of hashes: the pigeonhole rewrite of a Hamming join into equi joins.

Two 64-bit hashes within tau bits agree in at least one of tau + 1 bands. Hashes are made
distinct before the join, so a group of equal hashes is one row, and a
pair is reported from its first agreeing band only, so nothing is de-duplicated after.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def band_columns(hash_column: Column, bands: int) -> list[Column]:
    width, extra = divmod(64, bands)
    out, shift = [], 0
    for i in range(bands):
        size = width + (i < extra)
        out.append(
            F.shiftrightunsigned(hash_column, shift).bitwiseAND(F.lit((1 << size) - 1 if size < 64 else -1))
        )
        shift += size
    return out


def near_hashes(a: DataFrame, b: DataFrame, tau: int) -> DataFrame:
    """(hash_a, hash_b, distance) of distinct hashes within tau bits."""

    def banded(side: DataFrame, name: str) -> DataFrame:
        hashes = side.select("hash").distinct()
        keys = F.array(*band_columns(F.col("hash"), tau + 1))
        return hashes.select(F.col("hash").alias(name), F.posexplode(keys).alias("band", "key"))

    joined = banded(a, "hash_a").join(banded(b, "hash_b"), ["band", "key"])
    pairs = zip(band_columns(F.col("hash_a"), tau + 1), band_columns(F.col("hash_b"), tau + 1))
    first = F.coalesce(*[F.when(x == y, F.lit(i)) for i, (x, y) in enumerate(pairs)])
    far = F.bit_count(F.col("hash_a").bitwiseXOR(F.col("hash_b")))
    near = joined.where((far <= tau) & (F.col("band") == first))
    return near.select("hash_a", "hash_b", far.cast("int").alias("distance"))


def near_matches(a: DataFrame, b: DataFrame, tau: int) -> DataFrame:
    """(id_a, id_b, distance), id_a < id_b: members of near hashes.

    This lists every pair of members; where groups are large, use near_hashes with hash_index.
    """
    near = near_hashes(a, b, tau)
    left = a.select(F.col("image_id").alias("id_a"), F.col("hash").alias("hash_a"))
    right = b.select(F.col("image_id").alias("id_b"), F.col("hash").alias("hash_b"))
    return (
        left.join(near, "hash_a").join(right, "hash_b").where("id_a < id_b").select("id_a", "id_b", "distance")
    )
