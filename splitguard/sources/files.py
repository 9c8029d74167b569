"""Images and annotations from files, and the hash index as a table.

PGM and PPM, plain and binary, are decoded here, since no image library is assumed.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

IMAGE_SCHEMA = "path string, height int, width int, pixels array<int>, reason string"
ANNOTATION_SCHEMA = T.StructType(
    [
        T.StructField("images", T.ArrayType(T.StructType([
            T.StructField("id", T.LongType()), T.StructField("file_name", T.StringType()),
            T.StructField("height", T.IntegerType()), T.StructField("width", T.IntegerType()),
        ]))),
        T.StructField("annotations", T.ArrayType(T.StructType([
            T.StructField("id", T.LongType()), T.StructField("image_id", T.LongType()),
            T.StructField("category_id", T.LongType()),
            T.StructField("segmentation", T.ArrayType(T.ArrayType(T.DoubleType()))),
        ]))),
    ]
)
_HEADER = re.compile(rb"\A(P[2356])(?:\s+|#[^\n]*\n)+(\d+)(?:\s+|#[^\n]*\n)+(\d+)(?:\s+|#[^\n]*\n)+(\d+)\s", re.DOTALL)


def decode_netpbm(data: bytes) -> np.ndarray:
    """(height, width) grey cells of a PGM, or of a PPM by integer luma."""
    head = _HEADER.match(data)
    if not head:
        raise ValueError("no PGM or PPM header")
    magic, width, height, most = head[1], int(head[2]), int(head[3]), int(head[4])
    colours = 3 if magic in (b"P3", b"P6") else 1
    count = width * height * colours
    body = memoryview(data)[head.end() :]
    if magic in (b"P2", b"P3"):
        flat = np.array(bytes(body).split()[:count], np.int64)
    else:
        width_of = 2 if most > 255 else 1
        whole = bytes(body[: count * width_of])
        flat = np.frombuffer(whole[: len(whole) // width_of * width_of], ">u2" if most > 255 else np.uint8).astype(np.int64)
    if len(flat) < count:
        raise ValueError("the file ends early")
    if colours == 1:
        return flat.reshape(height, width)
    rgb = flat.reshape(height, width, 3)
    return (299 * rgb[..., 0] + 587 * rgb[..., 1] + 114 * rgb[..., 2]) // 1000


def read_rasters(spark: SparkSession, path: str, pattern: str = "*.p[gp]m") -> DataFrame:
    """IMAGE_SCHEMA rows of all matching files under path; a bad file has a reason and no pixels."""
    files = (
        spark.read.format("binaryFile")
        .option("recursiveFileLookup", "true")
        .option("pathGlobFilter", pattern)
        .load(path)
        .select("path", "content")
    )

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            grey, reasons = [], []
            for content in batch.column(1):
                try:
                    grey.append(decode_netpbm(content.as_buffer()))
                    reasons.append(None)
                except ValueError as bad:
                    grey.append(np.empty((0, 0), np.int64))
                    reasons.append(str(bad))
            missing = pa.array([r is not None for r in reasons], pa.bool_())
            ends = np.cumsum([0, *(g.size for g in grey)]).astype(np.int32)
            flat = np.concatenate([g.ravel() for g in grey] or [np.empty(0, np.int64)]).astype(np.int32)
            sides = [pa.array([g.shape[k] for g in grey], pa.int32(), mask=np.array([r is not None for r in reasons], bool)) for k in (0, 1)]
            pixels = pa.ListArray.from_arrays(pa.array(ends), pa.array(flat), mask=missing)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *sides, pixels, pa.array(reasons, pa.string())],
                names=["path", "height", "width", "pixels", "reason"],
            )

    return files.mapInArrow(kernel, IMAGE_SCHEMA)


class RasterSource(DataSource):
    """spark.read.format('raster').option('paths', 'a.pgm,b.pgm'): local files as grey rasters."""

    @classmethod
    def name(cls) -> str:
        return "raster"

    def schema(self) -> str:
        return IMAGE_SCHEMA

    def reader(self, schema):
        return _RasterReader([p for p in self.options.get("paths", "").split(",") if p])


class _RasterReader(DataSourceReader):
    def __init__(self, paths: list[str]):
        self.paths = paths

    def partitions(self):
        return [InputPartition(p) for p in self.paths]

    def read(self, partition):
        with open(partition.value, "rb") as f:
            data = f.read()
        try:
            grey = decode_netpbm(data)
        except ValueError as bad:
            yield partition.value, None, None, None, str(bad)
            return
        yield partition.value, grey.shape[0], grey.shape[1], grey.ravel().tolist(), None


def read_annotations(spark: SparkSession, path: str) -> DataFrame:
    """(image_id, file_name, annotation_id, category_id, points) of nested JSON annotations."""
    whole = spark.read.schema(ANNOTATION_SCHEMA).option("multiLine", "true").json(path)
    images = whole.select(F.inline("images")).select(F.col("id").alias("image_id"), "file_name")
    marks = whole.select(F.inline("annotations")).select(
        "image_id", F.col("id").alias("annotation_id"), "category_id",
        F.size(F.flatten("segmentation")).alias("points"),
    )
    return images.join(marks, "image_id", "left")


def read_hash_list(spark: SparkSession, path: str) -> DataFrame:
    """(image_id, hash) of a CSV list of ids and hexadecimal hashes."""
    from splitguard.operators.fingerprint import from_hex

    rows = spark.read.schema("image_id long, hash_hex string").csv(path, header=True)
    return rows.select("image_id", from_hex(F.col("hash_hex")).alias("hash"))


def write_index(hashed: DataFrame, path: str) -> None:
    """(image_id, split, hashes) as Parquet, a folder a split, so that a split is pruned by path."""
    hashed.write.mode("overwrite").partitionBy("split").parquet(path)


def write_bucketed_index(hashed: DataFrame, name: str, buckets: int) -> None:
    """(hash, image_id, split) as a table bucketed and sorted by hash: later audits need no shuffle."""
    flat = hashed.select(F.explode("hashes").alias("hash"), "image_id", "split")
    flat.write.mode("overwrite").bucketBy(buckets, "hash").sortBy("hash").saveAsTable(name)
