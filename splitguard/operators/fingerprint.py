"""Fingerprints: cosine-transform hashes, average hashes and content digests.

The kernel reads a collection (image_id, split, payload), rasterises, transforms and
thresholds in one pass over Arrow batches, and writes only longs. All orientations come from
one frequency block. A native twin builds the same bits from higher-order
functions alone, for checks and for clusters without Python workers.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitguard.functions.dct import (
    BASIS,
    SIDE,
    average_bits,
    bits_of,
    blocks_of,
    factor_blocks,
    orientation_tables,
    oriented,
    words_of,
)
from splitguard.functions.runtime import bind
from splitguard.operators.raster import RASTERISERS, by_size

#: Rows rasterised at once: 32 x 32 cells of 8 bytes each, so about 16 MB.
ROWS = 2000


@dataclass(frozen=True)
class Hash:
    """One output column: a cosine-transform hash, or an average hash with kind='ahash'."""

    name: str = "hash"
    kind: str = "phash"
    threshold: str = "mean_all"
    side: int = 8
    norm: str = "none"
    ops: tuple[str, ...] = ()  # with ops the column is an array, one hash an operation

    @property
    def type(self) -> str:
        wide = self.side * self.side > 64
        return "array<long>" if self.ops or wide else "long"


def hash_rasters(cells: np.ndarray, spec: Hash) -> np.ndarray:
    """(n, words or operations) signed longs."""
    if spec.kind == "ahash":
        return words_of(average_bits(cells, spec.side))
    blocks = blocks_of(cells, spec.side, spec.norm == "ortho")
    if spec.ops:
        if spec.side != 8:
            raise ValueError("oriented hashes have 64 bits")
        return np.concatenate(
            [words_of(bits_of(oriented(blocks, op), spec.threshold)) for op in spec.ops], axis=1
        )
    return words_of(bits_of(blocks, spec.threshold))


def hash_kernel(kind: str, *specs: Hash) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The kernel of fingerprints, for use alone or in a chain of kernels."""
    make = RASTERISERS[kind]

    def longs(cells: np.ndarray, spec: Hash) -> pa.Array:
        words = hash_rasters(cells, spec)
        flat = pa.array(words.reshape(-1), pa.int64())
        if spec.type == "long":
            return flat
        width = words.shape[1]
        return pa.ListArray.from_arrays(
            pa.array(np.arange(len(words) + 1, dtype=np.int32) * width), flat
        )

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["image_id", "split", *[s.name for s in specs]]
        for batch in batches:
            good = batch.filter(batch.column("payload").is_valid())
            for start in range(0, good.num_rows, ROWS):
                part = good.slice(start, ROWS)
                cells = make(part.column("payload"))
                columns = [part.column("image_id"), part.column("split")]
                columns += [longs(cells, s) for s in specs]
                yield pa.RecordBatch.from_arrays(columns, names=names)
            bad = batch.filter(batch.column("payload").is_null())
            if bad.num_rows:
                columns = [bad.column("image_id"), bad.column("split")]
                columns += [
                    pa.nulls(bad.num_rows, pa.int64() if s.type == "long" else pa.list_(pa.int64()))
                    for s in specs
                ]
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return kernel


def fingerprints(images: DataFrame, kind: str, *specs: Hash) -> DataFrame:
    """(image_id, split, one column a spec); a null payload gives null hashes."""
    schema = ", ".join(f"{s.name} {s.type}" for s in specs)
    slim = images.select("image_id", "split", "payload")
    return slim.mapInArrow(hash_kernel(kind, *specs), f"image_id long, split string, {schema}")


def phash(
    images: DataFrame,
    kind: str = "pixels",
    side: int = 8,
    threshold: str = "mean_all",
    norm: str = "none",
    ops: tuple[str, ...] = (),
) -> DataFrame:
    return fingerprints(images, kind, Hash("hash", "phash", threshold, side, norm, tuple(ops)))


def ahash(images: DataFrame, kind: str = "pixels", side: int = 8) -> DataFrame:
    return fingerprints(images, kind, Hash("hash", "ahash", side=side))


def freq_block(images: DataFrame, kind: str = "pixels", side: int = 8) -> DataFrame:
    """(image_id, split, block array<long>)."""
    make = RASTERISERS[kind]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = batch.filter(batch.column("payload").is_valid())
            for start in range(0, good.num_rows, ROWS):
                part = good.slice(start, ROWS)
                flat = blocks_of(make(part.column("payload")), side)
                ends = np.arange(part.num_rows + 1, dtype=np.int32) * side * side
                block = pa.ListArray.from_arrays(pa.array(ends), pa.array(flat.reshape(-1)))
                yield pa.RecordBatch.from_arrays(
                    [part.column("image_id"), part.column("split"), block],
                    names=["image_id", "split", "block"],
                )

    slim = images.select("image_id", "split", "payload")
    return slim.mapInArrow(kernel, "image_id long, split string, block array<long>")


def factor_kernel(
    factor: int, side: int = 8, threshold: str = "mean_all"
) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The kernel of phash_factor, for use alone or in a chain of kernels."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hashes = np.zeros(batch.num_rows, np.int64)
            reasons, groups = by_size(batch, side * factor)
            for rows, grey in groups:
                blocks = factor_blocks(grey, factor, side)
                hashes[rows] = words_of(bits_of(blocks, threshold))[:, 0]
            bad = np.array([r is not None for r in reasons], bool)
            yield pa.RecordBatch.from_arrays(
                [batch.column("image_id"), batch.column("split"), pa.array(hashes, pa.int64(), mask=bad)],
                names=["image_id", "split", "hash"],
            )

    return kernel


def phash_factor(
    images: DataFrame, factor: int, side: int = 8, threshold: str = "mean_all"
) -> DataFrame:
    """(image_id, split, hash) of (image_id, split, height, width, pixels), downsampled by a factor
    instead of fitted to 32 x 32. Rasters with fewer than `side` rows or columns left give nulls."""
    slim = images.select("image_id", "split", "height", "width", "pixels")
    return slim.mapInArrow(factor_kernel(factor, side, threshold), "image_id long, split string, hash long")


# ---- native twin -------------------------------------------------------------------


def _longs(values) -> Column:
    return F.array(*[F.lit(int(v)) for v in values])


def native_block(pixels: Column, side: int = 8) -> Column:
    """array<long> of side * side coefficients, from higher-order functions only."""
    basis = F.array(*[_longs(row) for row in BASIS[:side]])

    def dot(a: Column, b: Column) -> Column:
        return F.aggregate(
            F.zip_with(a, b, lambda x, y: x * y), F.lit(0).cast("long"), lambda acc, x: acc + x
        )

    rows = F.transform(
        F.sequence(F.lit(0), F.lit(SIDE - 1)),
        lambda y: F.transform(F.slice(pixels, y * SIDE + 1, F.lit(SIDE)), lambda g: g.cast("long")),
    )

    def contract(grid: Column, k: Column) -> Column:
        across = F.transform(k, lambda kv: F.transform(grid, lambda row: dot(row, kv)))  # [v][y]
        return bind(
            across,
            lambda t: F.flatten(F.transform(k, lambda ku: F.transform(t, lambda column: dot(column, ku)))),
        )

    return bind(rows, lambda grid: bind(basis, lambda k: contract(grid, k)))


def native_oriented(block: Column, op: str) -> Column:
    source, sign = orientation_tables(op)
    pairs = F.arrays_zip(_longs(source).alias("s"), _longs(sign).alias("g"))
    return F.transform(pairs, lambda p: F.element_at(block, (p["s"] + 1).cast("int")) * p["g"])


def native_bits(block: Column, threshold: str) -> Column:
    """64-bit hash of a block."""
    weights = _longs(
        np.array([1 << p for p in range(63)] + [-(1 << 63)], dtype=object)
    )

    def total(values: Column) -> Column:
        return F.aggregate(values, F.lit(0).cast("long"), lambda acc, x: acc + x)

    def packed(b: Column, limit: Column, factor: int, ac_only: bool) -> Column:
        picked = F.zip_with(
            b, weights, lambda t, w: F.when(factor * t > limit, w).otherwise(F.lit(0).cast("long"))
        )
        whole = total(picked)
        if not ac_only:
            return whole
        dc = F.when(factor * F.element_at(b, 1) > limit, F.lit(1)).otherwise(F.lit(0))
        return whole - dc

    def judge(b: Column) -> Column:
        if threshold == "mean_all":
            return bind(total(b), lambda s: packed(b, s, 64, False))
        if threshold == "mean_ac":
            return bind(total(b) - F.element_at(b, 1), lambda s: packed(b, s, 63, True))
        if threshold == "median_all":
            ranked = F.array_sort(b)
            return bind(
                bind(ranked, lambda r: F.element_at(r, 32) + F.element_at(r, 33)),
                lambda s: packed(b, s, 2, False),
            )
        return packed(b, F.lit(0).cast("long"), 1, True)

    return bind(block, judge)


def native_phash(images: DataFrame, threshold: str = "mean_all", ops: tuple[str, ...] = ()) -> DataFrame:
    """phash over pixel payloads without Python workers."""
    block = bind(native_block(F.col("payload")), lambda b: b)
    made = images.select("image_id", "split", block.alias("block"))
    if not ops:
        return made.select("image_id", "split", native_bits(F.col("block"), threshold).alias("hash"))
    hashes = bind(
        F.col("block"),
        lambda b: F.array(*[native_bits(native_oriented(b, op), threshold) for op in ops]),
    )
    return made.select("image_id", "split", hashes.alias("hash"))


# ---- other digests and formats ----------------------------------------------------


def content_digest(images: DataFrame, how: str = "sha2") -> DataFrame:
    """(image_id, split, digest) of the payload: the truth for exact copies."""
    payload = F.col("payload")
    kind = dict(images.dtypes)["payload"]
    if kind.startswith("array"):
        payload = F.to_json(payload)
    digest = F.md5(payload) if how == "md5" else F.sha2(payload, 256)
    return images.select("image_id", "split", digest.alias("digest"))


def hash_bits(hash_column: Column) -> Column:
    """64 characters, bit 63 first."""
    return F.lpad(F.bin(hash_column), 64, "0")


def hash_hex(hash_column: Column) -> Column:
    return F.lower(F.lpad(F.hex(hash_column), 16, "0"))


def from_hex(text: Column) -> Column:
    """Signed long of 16 hexadecimal digits."""
    high = F.conv(F.substring(text, 1, 8), 16, 10).cast("long")
    low = F.conv(F.substring(text, 9, 8), 16, 10).cast("long")
    return F.shiftleft(high, 32).bitwiseOR(low)


def hamming(a: Column, b: Column) -> Column:
    return F.bit_count(a.bitwiseXOR(b))
