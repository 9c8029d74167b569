"""Queries on the way of an image: colour, grey, fit to 32 x 32 or downsampling by a factor, hash.

The given tables hold no images, so each part has one made of its key by arithmetic: 48 x 40
colour cells, or 20 x 20 for every tenth, which is too small for a fingerprint. Cells are made,
turned grey, fitted and hashed in numpy by a chain of kernels in one Python pass, so that only keys
go in and only results come out. A table of parts is narrow and comes in few splits for the work
that hangs on its keys, so they are dealt out over all tasks first.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitguard import oracles as O
from splitguard.functions.dct import PAPER_OPS, size_basis
from splitguard.functions.runtime import reliable, shuffle_width
from splitguard.operators import fingerprint as fp
from splitguard.operators import measures, raster
from splitguard.sources.carriers import table

HEIGHT, WIDTH, SMALL = 48, 40, 20
# A cell of a colour: (k * a + key * b + (k div 40) * (key % c)) % 256.
_COLOURS = {"red": (7, 13, 5), "green": (3, 29, 11), "blue": (11, 5, 7)}
#: Images made at once: 1,920 cells of 4 bytes and three colours each, so about 12 MB.
IMAGES = 512

Kernel = Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]


def colour_cells(keys: np.ndarray, a: int, b: int, c: int) -> np.ndarray:
    """(n, 1920) cells of one colour; remainders have the sign of what is divided, as in SQL."""
    k = np.arange(HEIGHT * WIDTH)
    if len(keys) and keys.min() < 0:
        whole = k * a + (keys * b)[:, None] + (k // WIDTH) * np.fmod(keys, c)[:, None]
        return np.fmod(whole, 256).astype(np.int32)
    base, rows = (k * a).astype(np.int32), (k // WIDTH).astype(np.int32)
    return (base + (keys * b & 255).astype(np.int32)[:, None] + rows * (keys % c).astype(np.int32)[:, None]) & 255


def _colour_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(image_id, split, height, width, red, green, blue) of (image_id, split); no key, no colours."""
    k = np.arange(HEIGHT * WIDTH)
    for whole in batches:
        for part in (whole.slice(i, IMAGES) for i in range(0, whole.num_rows, IMAGES)):
            ids = part.column("image_id")
            keys = ids.fill_null(1).to_numpy(zero_copy_only=False)
            small = keys % 10 == 0
            high, wide = (np.where(small, SMALL, n).astype(np.int32) for n in (HEIGHT, WIDTH))
            sizes = (high * wide).astype(np.int64)
            filled = k < sizes[:, None]
            holes = np.repeat(ids.is_null().to_numpy(zero_copy_only=False), sizes) if ids.null_count else None
            lists = [
                raster.lists_of(pa.array(colour_cells(keys, *x)[filled], pa.int32(), mask=holes), sizes)
                for x in _COLOURS.values()
            ]
            yield pa.RecordBatch.from_arrays(
                [ids, part.column("split"), pa.array(high), pa.array(wide), *lists],
                names=["image_id", "split", "height", "width", *_COLOURS],
            )


def _grey_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(image_id, split, height, width, pixels)."""
    for batch in batches:
        grey = raster.grey_lists(*[batch.column(c) for c in _COLOURS])
        held = ["image_id", "split", "height", "width"]
        yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in held], grey], names=[*held, "pixels"])


def _payload_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """What a hash kernel reads, of fitted rasters."""
    for batch in batches:
        held = [batch.column(c) for c in ("image_id", "split", "pixels")]
        yield pa.RecordBatch.from_arrays(held, names=["image_id", "split", "payload"])


def made_images(spark, sf_dir, schema: str, *kernels: Kernel) -> DataFrame:
    """What the kernels, one after another, make of the colour images of all parts."""

    def chain(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for kernel in (_colour_batches, *kernels):
            batches = kernel(batches)
        return batches

    keys = table(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("image_id"))
    return raster.with_split(keys.repartition(shuffle_width(spark), "image_id")).mapInArrow(chain, schema)


def grey_modes_images(spark, sf_dir):
    modes = ("luma", "mean", "green")

    def texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rgb = [batch.column(c) for c in _COLOURS]
            made = [raster.joined_lists(raster.grey_lists(*rgb, mode)) for mode in modes]
            yield pa.RecordBatch.from_arrays([batch.column("image_id"), *made], names=["image_id", *modes])

    return made_images(spark, sf_dir, "image_id long, luma string, mean string, green string", texts)


def fit_images(spark, sf_dir):
    """Images fitted to 32 x 32, or why they can't be."""

    def texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = [batch.column("image_id"), batch.column("reason"), raster.joined_lists(batch.column("pixels"))]
            yield pa.RecordBatch.from_arrays(columns, names=["image_id", "reason", "cells"])

    return made_images(
        spark, sf_dir, "image_id long, reason string, cells string", _grey_batches, raster.fit_kernel(), texts
    )


def phash_images(spark, sf_dir):
    """Colour to hash; images that can't be fitted have none."""
    hashed = fp.hash_kernel("pixels", fp.Hash(threshold="mean_ac"))
    schema = "image_id long, split string, hash long"
    return made_images(spark, sf_dir, schema, _grey_batches, raster.fit_kernel(), _payload_batches, hashed)


def phash_factor_images(spark, sf_dir):
    """Colour to hash by a downsampling factor of two."""
    schema = "image_id long, split string, hash long"
    return made_images(spark, sf_dir, schema, _grey_batches, fp.factor_kernel(2, threshold="mean_ac"))


def wrong_sizes_images(spark, sf_dir):
    """How many images each reason leaves without a fingerprint, and how many hashes there are."""
    hashed = fp.hash_kernel("pixels", fp.Hash(threshold="mean_ac"))

    def counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            tally = pc.value_counts(batch.column("reason").fill_null("whole"))
            n = sum(h.num_rows - h.column("hash").null_count for h in hashed(_payload_batches(iter([batch]))))
            what, many = (tally.field(i).to_pylist() for i in (0, 1))
            yield pa.RecordBatch.from_arrays(
                [pa.array([*what, "hashed"], pa.string()), pa.array([*many, n], pa.int64())], names=["what", "n"]
            )

    found = made_images(spark, sf_dir, "what string, n long", _grey_batches, raster.fit_kernel(), counts)
    none = spark.range(1).select(F.lit("hashed").alias("what"), F.lit(0).cast("long").alias("n"))
    return found.unionByName(none).groupBy("what").agg(F.sum("n").alias("n"))


def index_size_images(spark, sf_dir):
    hashed = fp.hash_kernel("pixels", fp.Hash("hashes", threshold="mean_ac", ops=PAPER_OPS))
    schema = "image_id long, split string, hashes array<long>"
    kernels = (_grey_batches, raster.fit_kernel(), _payload_batches, hashed)
    return measures.index_size(reliable(made_images(spark, sf_dir, schema, *kernels)))


# ---- SQL twins ---------------------------------------------------------------------------


def _colour_sql() -> str:
    def cells(a: int, b: int, c: int) -> str:
        return f"list_transform(range(h * w), lambda k: (k * {a} + id * {b} + (k // {WIDTH}) * (id % {c})) % 256)"

    made = ", ".join(f"{cells(*x)} AS {n}" for n, x in _COLOURS.items())
    return f"""img AS MATERIALIZED (SELECT id AS image_id, {O.split_case('id')} AS split, h, w, {made} FROM (
    SELECT p_partkey AS id, CASE WHEN p_partkey % 10 = 0 THEN {SMALL} ELSE {HEIGHT} END AS h,
           CASE WHEN p_partkey % 10 = 0 THEN {SMALL} ELSE {WIDTH} END AS w FROM part))"""


_LUMA = "list_transform(range(1, h * w + 1), lambda i: (299 * red[i] + 587 * green[i] + 114 * blue[i]) // 1000)"


def _grey_sql() -> str:
    return f"{_colour_sql()}, grey AS MATERIALIZED (SELECT image_id, split, h, w, {_LUMA} AS p FROM img)"


def _product(source: str, cells: str, high: int, wide: int, down, across, out: str) -> str:
    """out(image_id, split, b): down x cells x across transposed, row by row."""
    rows = ", ".join(
        f"list_transform(range({high}), lambda y: list_dot_product(c[{wide} * y + 1 : {wide} * y + {wide}], {O.listed(r)}::DOUBLE[])) AS t{j}"
        for j, r in enumerate(across)
    )
    dots = ", ".join(f"list_dot_product({O.listed(r)}::DOUBLE[], t{j})" for r in down for j in range(len(across)))
    return f"""{out}_c AS MATERIALIZED (SELECT image_id, split, ({cells})::DOUBLE[] AS c FROM {source}),
{out}_t AS MATERIALIZED (SELECT image_id, split, {rows} FROM {out}_c),
{out} AS MATERIALIZED (SELECT image_id, split, [{dots}]::BIGINT[] AS b FROM {out}_t)"""


def _fitted_sql() -> str:
    down, across = raster.area_weights(HEIGHT), raster.area_weights(WIDTH)
    return f"""{_grey_sql()}, whole AS (SELECT * FROM grey WHERE h >= 32 AND w >= 32),
{_product('whole', 'p', HEIGHT, WIDTH, down, across, 'sums')},
ras AS MATERIALIZED (SELECT image_id, split, list_transform(b, lambda x: 16 * x // {HEIGHT * WIDTH}) AS g FROM sums)"""


def _factor_sql() -> str:
    """Hashes of both sizes, each downsampled by two."""
    parts = []
    for name, h, w in (("large", HEIGHT, WIDTH), ("little", SMALL, SMALL)):
        high, wide = h // 2, w // 2
        corner = f"(i // {wide}) * {2 * w} + (i % {wide}) * 2"
        box = " + ".join(f"p[{corner} + {at + 1}]" for at in (0, 1, w, w + 1))
        boxes = f"list_transform(range({high * wide}), lambda i: {box})"
        parts.append(f"{name}_p AS (SELECT * FROM grey WHERE h = {h})")
        parts.append(_product(f"{name}_p", boxes, high, wide, size_basis(high), size_basis(wide), name))
    both = "blk AS MATERIALIZED (SELECT * FROM large UNION ALL SELECT * FROM little)"
    return ", ".join([_grey_sql(), *parts, both, O.version_ctes("mean_ac")])


def entries():
    hashed = f"{_fitted_sql()}, {O.block_ctes()}, {O.version_ctes('mean_ac')}"
    versions = f"{_fitted_sql()}, {O.block_ctes()}, {O.version_ctes('mean_ac', PAPER_OPS)}"
    every = "SELECT grey.image_id, grey.split, hash FROM grey LEFT JOIN v USING (image_id)"
    return {
        "grey_modes_images": (grey_modes_images, O.with_(_colour_sql(), f"""SELECT image_id, array_to_string({_LUMA}, ',') AS luma,
    array_to_string(list_transform(range(1, h * w + 1), lambda i: (red[i] + green[i] + blue[i]) // 3), ',') AS mean,
    array_to_string(green, ',') AS green FROM img""")),
        "fit_images": (fit_images, O.with_(_fitted_sql(), """SELECT image_id, CASE WHEN h < 32 OR w < 32 THEN 'smaller than the target' END AS reason,
    array_to_string(g, ',') AS cells FROM grey LEFT JOIN ras USING (image_id)""")),
        "phash_images": (phash_images, O.with_(hashed, every)),
        "phash_factor_images": (phash_factor_images, O.with_(_factor_sql(), "SELECT image_id, split, hash FROM v")),
        "wrong_sizes_images": (wrong_sizes_images, """SELECT CASE WHEN p_partkey % 10 = 0 THEN 'smaller than the target' ELSE 'whole' END AS what, count(*) AS n
FROM part GROUP BY 1 UNION ALL SELECT 'hashed', count(*) FILTER (p_partkey % 10 <> 0) FROM part"""),
        "index_size_images": (index_size_images, O.with_(versions, """SELECT (SELECT count(*) FROM part) AS n_images, count(*) AS n_versions,
    count(DISTINCT hash) AS n_keys, 8.0::DOUBLE * count(*) / (SELECT count(*) FROM part) AS bytes_an_image, 24 AS bytes_a_key FROM v""")),
    }
