"""Orientations of rasters and of their hashes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitguard.functions.dct import ALL_OPS, PAPER_OPS, pixel_source
from splitguard.operators.fingerprint import Hash, fingerprints

__all__ = ["ALL_OPS", "PAPER_OPS", "explode_versions", "orient", "orientation_hashes"]


def orient(images: DataFrame, ops: tuple[str, ...] = PAPER_OPS) -> DataFrame:
    """(image_id, split, op, payload): one row an operation, by moving 32 x 32 pixels."""
    moves = F.array(
        *[
            F.struct(
                F.lit(op).alias("op"),
                F.array(*[F.lit(int(i) + 1) for i in pixel_source(op)]).alias("source"),
            )
            for op in ops
        ]
    )
    spread = images.select("image_id", "split", "payload", F.explode(moves).alias("m"))
    moved = F.transform("m.source", lambda i: F.element_at("payload", i))
    return spread.select("image_id", "split", F.col("m.op").alias("op"), moved.alias("payload"))


def orientation_hashes(
    images: DataFrame, kind: str, ops: tuple[str, ...] = PAPER_OPS, threshold: str = "mean_all"
) -> DataFrame:
    """(image_id, split, hashes array<long>), all from one frequency block."""
    return fingerprints(images, kind, Hash("hashes", threshold=threshold, ops=tuple(ops)))


def explode_versions(hashed: DataFrame, ops: tuple[str, ...] = PAPER_OPS) -> DataFrame:
    """(image_id, split, op, hash) of (image_id, split, hashes)."""
    names = F.array(*[F.lit(op) for op in ops])
    spread = hashed.select("image_id", "split", F.posexplode("hashes").alias("nth", "hash"))
    return spread.select(
        "image_id", "split", F.element_at(names, F.col("nth") + 1).alias("op"), "hash"
    )
