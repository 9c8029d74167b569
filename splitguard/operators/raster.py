"""Making, cutting and editing rasters.

A raster is a row-major array of integer grey cells. Collections are rows
(image_id, split, payload): the payload is what a rasteriser reads (a text, a vector or
pixels), so that a fingerprint kernel can rasterise and hash in one pass over Arrow
batches without writing pixels to a shuffle or a second Python stage.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitguard.functions.dct import SIDE

RATIOS = (14, 3, 3)
SPLITS = ("train", "val", "test")


def split_of(key: Column, ratios: tuple[int, int, int] = RATIOS) -> Column:
    """train, val or test by the remainder of an id; 70/15/15 by default."""
    train, val, _ = ratios
    part = F.pmod(key.cast("long"), F.lit(sum(ratios)))
    return F.when(part < train, "train").when(part < train + val, "val").otherwise("test")


def with_split(df: DataFrame, key: str = "image_id", ratios=RATIOS) -> DataFrame:
    return df.withColumn("split", split_of(F.col(key), ratios))


def flat_values(column: pa.Array) -> np.ndarray:
    """All cells of a column of lists, end to end, without a Python object for any of them."""
    return column.flatten().to_numpy(zero_copy_only=False)


# ---- rasterisers over Arrow columns: (n,) payloads -> (n, 32, 32) integers ---------


def scan_rasters(column: pa.Array) -> np.ndarray:
    """Bytes of a whole text laid over 64 x 64 pixels in reading order, then 2 x 2 box sums.

    A pixel is the mean, rounded down, of the bytes that fall on it; of a text with fewer bytes
    than pixels, a byte falls on several.
    """
    out = np.zeros((len(column), SIDE, SIDE), np.int64)
    grid = np.arange(4 * SIDE * SIDE + 1, dtype=np.int64)
    for i, value in enumerate(column):
        text = value.as_py()
        data = text.encode("utf-8", "surrogatepass") if isinstance(text, str) else text
        if not data:
            continue
        cells, edges = np.frombuffer(data, np.uint8), (grid * len(data)) >> 12
        if len(data) <= 4 * SIDE * SIDE:
            cells = cells[edges[:-1]]
        else:
            cells = np.add.reduceat(cells, edges[:-1], dtype=np.int64) // np.diff(edges)
        out[i] = cells.reshape(SIDE, 2, SIDE, 2).sum(axis=(1, 3), dtype=np.int64)
    return out


def vector_rasters(column: pa.Array) -> np.ndarray:
    """64 numbers as 8 x 8 grey cells, each repeated to 4 x 4."""
    flat = flat_values(column).astype(float).reshape(len(column), 8, 8)
    grey = np.clip(np.floor(flat * 255 + 127.5), 0, 255).astype(np.int64)
    return grey.repeat(4, axis=1).repeat(4, axis=2)


def bigram_rasters(column: pa.Array) -> np.ndarray:
    """Counts of successive byte pairs, 32 classes of eight bytes, scaled to the length."""
    out = np.zeros((len(column), SIDE, SIDE), np.int64)
    for i, value in enumerate(column):
        data = np.frombuffer((value.as_py() or "").encode("utf-8", "surrogatepass"), np.uint8)
        if len(data) < 2:
            continue
        kinds = data.astype(np.int64) >> 3
        counts = np.bincount(kinds[:-1] * SIDE + kinds[1:], minlength=SIDE * SIDE)
        out[i] = (counts * 4096 // (len(data) - 1)).reshape(SIDE, SIDE)
    return out


def pixel_rasters(column: pa.Array) -> np.ndarray:
    return flat_values(column).astype(np.int64).reshape(len(column), SIDE, SIDE)


RASTERISERS: dict[str, Callable[[pa.Array], np.ndarray]] = {
    "text": scan_rasters,
    "vector": vector_rasters,
    "bigram": bigram_rasters,
    "pixels": pixel_rasters,
}


def rasters(images: DataFrame, kind: str) -> DataFrame:
    """(image_id, split, pixels array<int>) of a collection; rows without a payload give nulls."""
    make = RASTERISERS[kind]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            whole = batch.filter(batch.column("payload").is_valid())
            for part in (whole, batch.filter(batch.column("payload").is_null())):
                if not part.num_rows:
                    continue
                if part is whole:
                    flat = make(part.column("payload")).reshape(-1).astype(np.int32)
                    ends = np.arange(part.num_rows + 1, dtype=np.int32) * SIDE * SIDE
                    pixels = pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))
                else:
                    pixels = pa.nulls(part.num_rows, pa.list_(pa.int32()))
                yield pa.RecordBatch.from_arrays(
                    [part.column("image_id"), part.column("split"), pixels],
                    names=["image_id", "split", "pixels"],
                )

    slim = images.select("image_id", "split", "payload")
    return slim.mapInArrow(kernel, "image_id long, split string, pixels array<int>")


# ---- DataFrame expressions over arrays of cells -----------------------------------


def to_grey(red: Column, green: Column, blue: Column, mode: str = "luma") -> Column:
    """Grey array from three arrays of colour cells, in integers."""
    if mode == "green":
        return green
    rgb = F.arrays_zip(red.alias("r"), green.alias("g"), blue.alias("b"))
    if mode == "mean":
        return F.transform(rgb, lambda c: F.floor((c["r"] + c["g"] + c["b"]) / 3).cast("int"))
    if mode != "luma":
        raise ValueError("mode must be luma, green or mean")
    return F.transform(
        rgb, lambda c: F.floor((299 * c["r"] + 587 * c["g"] + 114 * c["b"]) / 1000).cast("int")
    )


def list_sizes(column: pa.ListArray) -> np.ndarray:
    """The number of cells of each list, of a null list zero."""
    return pc.fill_null(pc.list_value_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)


def lists_of(values: pa.Array, sizes: np.ndarray, mask: pa.Array | None = None) -> pa.ListArray:
    """A column of lists of these sizes from all their values, end to end; null where the mask is set."""
    ends = np.concatenate(([0], np.cumsum(sizes))).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), values, mask=mask)


def grey_lists(red: pa.ListArray, green: pa.ListArray, blue: pa.ListArray, mode: str = "luma") -> pa.ListArray:
    """to_grey over Arrow columns of lists of the same sizes; a cell without all its colours is null."""
    if mode == "green":
        return green
    if mode not in ("luma", "mean"):
        raise ValueError("mode must be luma, green or mean")
    colours = [c.flatten() for c in (red, green, blue)]
    r, g, b = (c.fill_null(0).to_numpy(zero_copy_only=False) for c in colours)
    grey = (299 * r + 587 * g + 114 * b) // 1000 if mode == "luma" else (r + g + b) // 3
    holes = None
    if any(c.null_count for c in colours):
        holes = np.logical_or.reduce([c.is_null().to_numpy(zero_copy_only=False) for c in colours])
    return lists_of(pa.array(grey.astype(np.int32), mask=holes), list_sizes(red), red.is_null() if red.null_count else None)


def joined_lists(cells: pa.ListArray) -> pa.StringArray:
    """The cells of each list as one text with commas; null cells are left out, a null list is null."""
    sizes, values = list_sizes(cells), cells.flatten()
    if values.null_count:
        held = values.is_valid().to_numpy(zero_copy_only=False)
        upto = np.concatenate(([0], np.cumsum(held)))
        ends = np.cumsum(sizes)
        sizes, values = upto[ends] - upto[ends - sizes], values.drop_null()
    if len(values):
        least, most = (x.as_py() for x in pc.min_max(values).values())
        if most - least < 1 << 16:  # few different numbers: each is written once
            words = pa.array(np.arange(least, most + 1)).cast(pa.string())
            words = words.take(pa.array(values.to_numpy() - least))
        else:
            words = values.cast(pa.string())
    else:
        words = pa.array([], pa.string())
    texts = pc.binary_join(lists_of(words, sizes), ",")
    return pc.if_else(cells.is_valid(), texts, None) if cells.null_count else texts


def box_downsample(pixels: Column, height: int, width: int, factor: int) -> Column:
    """Sums of factor x factor boxes; both sides must be multiples of the factor."""
    if height % factor or width % factor:
        raise ValueError("sides must be multiples of the factor")
    out_width = width // factor

    def cell(k: Column) -> Column:
        top, left = F.floor(k / out_width).cast("int") * factor, F.pmod(k, F.lit(out_width)) * factor
        picks = [
            F.element_at(pixels, (top + dy) * width + left + dx + 1)
            for dy in range(factor)
            for dx in range(factor)
        ]
        return sum(picks[1:], picks[0])

    return F.transform(F.sequence(F.lit(0), F.lit(out_width * (height // factor) - 1)), cell)


def area_weights(size: int, side: int = SIDE) -> np.ndarray:
    """weights[i][x]: 32nds of source cell x that fall into target cell i, in integers."""
    edges = np.arange(side + 1) * size  # in units of 1 / side of a source cell
    cells = np.arange(size)
    low = np.maximum(edges[:-1, None], cells * side)
    high = np.minimum(edges[1:, None], (cells + 1) * side)
    return np.maximum(0, high - low)


def fit_array(grey: np.ndarray, side: int = SIDE) -> np.ndarray:
    """(height, width) -> (side, side): area means with four fractional bits."""
    high, wide = grey.shape
    weighted = area_weights(high, side) @ grey.astype(np.int64) @ area_weights(wide, side).T
    return 16 * weighted // (high * wide)


def by_size(batch: pa.RecordBatch, least: int) -> tuple[list[str | None], Iterator[tuple[np.ndarray, np.ndarray]]]:
    """(reason why a row is no raster, or None, a row; (rows, (n, height, width) cells) a size).

    A raster has least x least cells at least, fills its sides and has no null cell.
    """
    def sides(name: str) -> np.ndarray:
        return batch.column(name).fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)

    pixels, high, wide = batch.column("pixels"), sides("height"), sides("width")
    sizes = pc.fill_null(pc.list_value_length(pixels), -1).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = pixels.flatten()
    begins = np.cumsum(np.maximum(sizes, 0)) - np.maximum(sizes, 0)
    holes = np.zeros(len(sizes), bool)
    if flat.null_count:
        at = np.flatnonzero(flat.is_null().to_numpy(zero_copy_only=False))
        holes[np.searchsorted(begins + np.maximum(sizes, 0), at, "right")] = True
    cells = flat.fill_null(0).to_numpy(zero_copy_only=False)
    tests = [
        ("no pixels", (sizes < 0) | (high < 0) | (wide < 0)),
        ("pixels do not fill the raster", sizes != high * wide),
        ("smaller than the target", np.minimum(high, wide) < least),
        ("null pixel", holes),
    ]
    reasons = [next((name for name, bad in tests if bad[i]), None) for i in range(len(sizes))]
    good = np.array([r is None for r in reasons], bool)

    def groups() -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for h, w in sorted(set(zip(high[good].tolist(), wide[good].tolist()))):
            rows = np.flatnonzero(good & (high == h) & (wide == w))
            step = max(1, (1 << 22) // (h * w))  # 32 MB of cells at once
            for part in (rows[i : i + step] for i in range(0, len(rows), step)):
                yield part, cells[begins[part][:, None] + np.arange(h * w)].reshape(len(part), h, w)

    return reasons, groups()


def fit_many(grey: np.ndarray, side: int = SIDE) -> np.ndarray:
    """fit_array of (n, height, width) rasters; all sums are exact in double precision."""
    high, wide = grey.shape[1:]
    down, across = area_weights(high, side).astype(float), area_weights(wide, side).astype(float)
    sums = np.rint(down @ (grey.astype(float) @ across.T)).astype(np.int64)
    return 16 * sums // (high * wide)


def fit_kernel(side: int = SIDE, on_bad: str = "null") -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The kernel of fit_rasters, for use alone or in a chain of kernels."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            reasons, groups = by_size(batch, side)
            if on_bad == "raise" and any(reasons):
                raise ValueError(next(r for r in reasons if r))
            cells = np.zeros((batch.num_rows, side * side), np.int32)
            for rows, grey in groups:
                cells[rows] = fit_many(grey, side).reshape(len(rows), side * side)
            bad = np.array([r is not None for r in reasons], bool)
            ends = np.arange(batch.num_rows + 1, dtype=np.int32) * side * side
            pixels = pa.ListArray.from_arrays(pa.array(ends), pa.array(cells.reshape(-1)), mask=pa.array(bad))
            yield pa.RecordBatch.from_arrays(
                [batch.column("image_id"), batch.column("split"), pixels, pa.array(reasons, pa.string())],
                names=["image_id", "split", "pixels", "reason"],
            )

    return kernel


def fit_rasters(images: DataFrame, side: int = SIDE, on_bad: str = "null") -> DataFrame:
    """(image_id, split, pixels, reason) from (image_id, split, height, width, pixels).

    Images under side x side, of the wrong number of cells or with null cells give null
    pixels and a reason, or raise with on_bad='raise'.
    """
    slim = images.select("image_id", "split", "height", "width", "pixels")
    return slim.mapInArrow(
        fit_kernel(side, on_bad), "image_id long, split string, pixels array<int>, reason string"
    )


def tile_patches(tiles: DataFrame, height: int, width: int, patch_h: int, patch_w: int) -> DataFrame:
    """(tile_id, r, c, pixels): non-overlapping patches of (tile_id, pixels); rests are left out."""
    rows, cols = height // patch_h, width // patch_w
    spread = tiles.repartition("tile_id").select(
        "tile_id",
        "pixels",
        F.explode(F.sequence(F.lit(0), F.lit(rows * cols - 1))).alias("k"),
    )
    placed = spread.select(
        "tile_id", "pixels", F.expr(f"cast(k div {cols} as int)").alias("r"), F.expr(f"k % {cols}").alias("c")
    )
    strips = F.transform(
        F.sequence(F.lit(0), F.lit(patch_h - 1)),
        lambda y: F.slice(
            F.col("pixels"), (F.col("r") * patch_h + y) * width + F.col("c") * patch_w + 1, F.lit(patch_w)
        ),
    )
    return placed.select("tile_id", "r", "c", F.flatten(strips).alias("pixels"))


def text_patches(docs: DataFrame, key: str, text: str, size: int) -> DataFrame:
    """(image_id, patch_no, patch): whole texts cut into stretches of a fixed number of characters."""
    length = F.char_length(text)
    starts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.expr(f"(char_length({text}) - 1) div {size}")))
    body = docs.where(length > 0).select(
        F.col(key).cast("long").alias("image_id"), F.col(text).alias("body"), F.explode(starts).alias("k")
    )
    return body.select(
        "image_id",
        F.col("k").cast("int").alias("patch_no"),
        F.substring("body", F.col("k").cast("int") * size + 1, F.lit(size)).alias("patch"),
    )


def grid_raster(df: DataFrame, key: str, row: Column, col: Column, value: Column) -> DataFrame:
    """(image_id, split, payload): one 32 x 32 raster a key from sums of value by cell.

    Cells are summed before anything is gathered; a key gathers at most 1,024 of them.
    """
    cells = df.select(
        F.col(key).cast("long").alias("image_id"), (row * SIDE + col).cast("int").alias("cell"), value.alias("v")
    )
    summed = cells.groupBy("image_id", "cell").agg(F.sum("v").cast("int").alias("v"))
    gathered = summed.groupBy("image_id").agg(
        F.map_from_entries(F.collect_list(F.struct("cell", "v"))).alias("cells")
    )
    pixels = F.transform(
        F.sequence(F.lit(0), F.lit(SIDE * SIDE - 1)),
        lambda i: F.coalesce(F.try_element_at("cells", i), F.lit(0)),
    )
    return with_split(gathered.select("image_id", pixels.alias("payload"))).select(
        "image_id", "split", "payload"
    )


def radiometric(pixels: Column, gain: int, bias: int, clip: bool = False) -> Column:
    """gain * cell + bias, cell by cell."""
    edit = F.transform(pixels, lambda g: g * gain + bias)
    return F.transform(edit, lambda g: F.least(F.greatest(g, F.lit(0)), F.lit(255))) if clip else edit


def perturb_cells(pixels: Column, key: Column, k: int, seed: int = 0) -> Column:
    """k cells, picked by arithmetic from the key, overwritten with the cell's complement to 255."""

    def edit(value: Column, i: Column) -> Column:
        place = F.pmod((i + key * 31 + seed) * 1013, F.lit(SIDE * SIDE))  # odd: a permutation
        return F.when(place < k, 255 - value).otherwise(value)

    return F.transform(pixels, edit)
