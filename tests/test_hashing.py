"""Rasters, transforms and fingerprints: exactness and invariances."""

import math
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from splitguard.functions import dct
from splitguard.operators import fingerprint as fp
from splitguard.operators import raster
from splitguard.operators.orient import ALL_OPS, PAPER_OPS, explode_versions, orient, orientation_hashes

RNG = np.random.default_rng(3)
CELLS = RNG.integers(0, 256, (12, 32, 32))


@pytest.fixture(scope="module")
def pixels(spark):
    rows = [(i, ("train", "val", "test")[i % 3], c.ravel().tolist()) for i, c in enumerate(CELLS)]
    return spark.createDataFrame(rows, "image_id long, split string, payload array<int>").cache()


def by_id(df, column="hash"):
    return {r["image_id"]: r[column] for r in df.collect()}


def test_basis_is_stable_and_antisymmetric():
    exact = [[8192 * math.cos((2 * x + 1) * u * math.pi / 64) for x in range(32)] for u in range(16)]
    assert min(abs(v - math.floor(v) - 0.5) for row in exact for v in row) > 0.0015
    for u in range(16):
        assert (dct.BASIS[u, ::-1] == (-1) ** u * dct.BASIS[u]).all()
    assert (dct.BASIS[1:].sum(axis=1) == 0).all()
    assert dct.MOST_CELL == 131072


def test_block_is_exact():
    k = dct.BASIS[:8].astype(object)
    for side in (8, 16):
        k = dct.BASIS[:side].astype(object)
        for cells, block in zip(CELLS, dct.blocks_of(CELLS, side)):
            assert (k @ cells.astype(object) @ k.T).ravel().tolist() == block.tolist()
    with pytest.raises(ValueError):
        dct.blocks_of(np.full((1, 32, 32), -1))


@pytest.mark.parametrize("op", ALL_OPS)
def test_orientation_of_the_block_is_that_of_the_pixels(op):
    turned = CELLS.reshape(len(CELLS), -1)[:, dct.pixel_source(op)].reshape(CELLS.shape)
    assert (dct.oriented(dct.blocks_of(CELLS), op) == dct.blocks_of(turned)).all()


def test_turns_and_mirrors_form_a_group():
    cells = np.arange(1024)
    four = cells
    for _ in range(4):
        four = four[dct.pixel_source("r90")]
    assert (four == cells).all()
    for op in ("flip_lr", "flip_tb", "r180", "transpose", "anti"):
        assert (cells[dct.pixel_source(op)][dct.pixel_source(op)] == cells).all()


@pytest.mark.parametrize("threshold", dct.THRESHOLDS)
def test_bits_follow_their_rule(threshold):
    blocks = dct.blocks_of(CELLS)
    words = dct.words_of(dct.bits_of(blocks, threshold))[:, 0]
    for block, word in zip(blocks.tolist(), words.tolist()):
        ac = block[1:]
        ranked = sorted(block)
        limit = {
            "mean_all": Fraction(sum(block), 64),
            "mean_ac": Fraction(sum(ac), 63),
            "median_all": Fraction(ranked[31] + ranked[32], 2),
            "sign_ac": Fraction(0),
        }[threshold]
        bits = [t > limit for t in block]
        if threshold.endswith("_ac"):
            bits[0] = False
        assert sum(1 << p for p, b in enumerate(bits) if b) == word % (1 << 64)


@pytest.mark.parametrize("threshold", dct.THRESHOLDS)
def test_native_kernel_gives_the_same_bits(pixels, threshold):
    few = pixels.where("image_id < 4")
    assert by_id(fp.native_phash(few, threshold)) == by_id(fp.phash(few, threshold=threshold))
    native = by_id(fp.native_phash(few, threshold, ALL_OPS))
    assert native == by_id(fp.phash(few, threshold=threshold, ops=ALL_OPS))


def test_contrast_and_brightness(pixels):
    for threshold in dct.THRESHOLDS:
        base = by_id(fp.phash(pixels, threshold=threshold))
        doubled = pixels.withColumn("payload", raster.radiometric(F.col("payload"), 2, 0))
        assert by_id(fp.phash(doubled, threshold=threshold)) == base
        if threshold != "mean_all":  # a shift moves only the first coefficient
            brighter = pixels.withColumn("payload", raster.radiometric(F.col("payload"), 1, 10))
            if threshold != "median_all":
                assert by_id(fp.phash(brighter, threshold=threshold)) == base
    clipped = pixels.select(raster.radiometric(F.col("payload"), 3, 0, clip=True).alias("p"))
    assert max(max(r["p"]) for r in clipped.collect()) == 255


def test_average_hash(pixels):
    got = by_id(fp.ahash(pixels))
    for i, cells in enumerate(CELLS):
        means = [Fraction(int(cells[y : y + 4, x : x + 4].sum()), 16) for y in range(0, 32, 4) for x in range(0, 32, 4)]
        whole = Fraction(int(cells.sum()), 1024)
        assert got[i] % (1 << 64) == sum(1 << p for p, m in enumerate(means) if m > whole)


def test_wide_and_scaled_hashes(pixels):
    deep = by_id(fp.phash(pixels, side=16, threshold="mean_ac"))
    assert all(len(h) == 4 for h in deep.values())
    assert all(len(h) == 3 for h in by_id(fp.phash(pixels, side=12)).values())
    weights = np.outer(dct.ortho_weights(8), dct.ortho_weights(8)).ravel()
    assert (dct.blocks_of(CELLS, ortho=True) == dct.blocks_of(CELLS) * weights).all()
    assert abs(12 / 17 - math.sqrt(0.5)) < 0.0015


def test_versions_and_pixel_path_agree(pixels):
    derived = explode_versions(orientation_hashes(pixels, "pixels", PAPER_OPS), PAPER_OPS)
    moved = orient(pixels, PAPER_OPS).select("image_id", F.col("op").alias("split"), "payload")
    a = {(r["image_id"], r["op"]): r["hash"] for r in derived.collect()}
    b = {(r["image_id"], r["split"]): r["hash"] for r in fp.phash(moved).collect()}
    assert a == b and len(a) == 6 * len(CELLS)


def test_formats(spark):
    values = [0, 1, -1, -(1 << 63), (1 << 63) - 1, 0x0123456789ABCDEF]
    df = spark.createDataFrame([(v,) for v in values], "h long")
    for r in df.select("h", fp.hash_hex(F.col("h")).alias("x"), fp.hash_bits(F.col("h")).alias("b"), fp.from_hex(fp.hash_hex(F.col("h"))).alias("back")).collect():
        assert r["x"] == f"{r['h'] % (1 << 64):016x}" and r["b"] == f"{r['h'] % (1 << 64):064b}" and r["back"] == r["h"]


def test_odd_payloads(spark):
    rows = [(1, "train", None), (2, "train", ""), (3, "train", "x"), (3, "train", "x"), (4, "val", "é" * 70000)]
    texts = spark.createDataFrame(rows, "image_id long, split string, payload string")
    got = fp.phash(texts, "text", threshold="mean_ac").collect()
    assert sorted((r["image_id"], r["hash"] is None) for r in got) == [(1, True), (2, False), (3, False), (3, False), (4, False)]
    assert by_id(fp.phash(texts, "text", threshold="mean_ac"))[2] == 0  # a flat raster has no bits
    assert fp.phash(texts.limit(0), "text").count() == 0
    assert by_id(raster.rasters(texts, "text"), "pixels")[1] is None
    constant = spark.createDataFrame([(1, "train", [7] * 1024)], "image_id long, split string, payload array<int>")
    assert by_id(fp.phash(constant, threshold="mean_ac"))[1] == 0
    assert by_id(fp.phash(constant, threshold="mean_all"))[1] == 1


def test_scan_raster_by_hand():
    import pyarrow as pa

    text = "".join(chr(33 + i % 90) for i in range(777))
    got = raster.scan_rasters(pa.array([text]))[0]
    big = [ord(text[(i * 777) // 4096]) for i in range(4096)]
    want = [[sum(big[(2 * y + a) * 64 + 2 * x + b] for a in (0, 1) for b in (0, 1)) for x in range(32)] for y in range(32)]
    assert got.tolist() == want


@pytest.mark.parametrize("size", [(32, 32), (33, 47), (300, 64)])
def test_fit_is_the_area_mean(size):
    grey = RNG.integers(0, 256, size)
    got = raster.fit_array(grey)
    h, w = size
    for i, j in ((0, 0), (31, 31), (5, 17)):
        total = Fraction(0)
        for y in range(h):
            for x in range(w):
                a = max(Fraction(0), min(Fraction((i + 1) * h, 32), y + 1) - max(Fraction(i * h, 32), y))
                b = max(Fraction(0), min(Fraction((j + 1) * w, 32), x + 1) - max(Fraction(j * w, 32), x))
                total += a * b * int(grey[y, x])
        assert got[i, j] == math.floor(16 * total / (Fraction(h, 32) * Fraction(w, 32)))


def test_fit_rasters_guards(spark):
    rows = [(1, "train", 32, 40, [1] * 1280), (2, "train", 8, 8, [1] * 64), (3, "train", 32, 32, [1] * 7), (4, "train", None, 3, None), (5, "train", 32, 32, [None] * 1024)]
    images = spark.createDataFrame(rows, "image_id long, split string, height int, width int, pixels array<int>")
    got = {r["image_id"]: (r["pixels"], r["reason"]) for r in raster.fit_rasters(images).collect()}
    assert got[1] == ([16] * 1024, None)
    assert all(got[i][0] is None and got[i][1] for i in (2, 3, 4, 5))
    with pytest.raises(Exception, match="smaller than the target"):
        raster.fit_rasters(images.where("image_id = 2"), on_bad="raise").collect()
    by_factor = by_id(fp.phash_factor(images, 2, threshold="mean_ac"))
    assert by_factor[1] is not None and by_factor[2] is None


def test_grey_box_patches_and_edits(spark):
    df = spark.createDataFrame([([0, 100, 255], [10, 100, 255], [20, 100, 0])], "r array<int>, g array<int>, b array<int>")
    modes = {m: df.select(raster.to_grey(F.col("r"), F.col("g"), F.col("b"), m).alias("x")).first()["x"] for m in ("luma", "green", "mean")}
    assert modes == {"luma": [8, 100, 225], "green": [10, 100, 255], "mean": [10, 100, 170]}
    tiles = spark.createDataFrame([(1, list(range(48)))], "tile_id long, pixels array<int>")
    box = tiles.select(raster.box_downsample(F.col("pixels"), 6, 8, 2).alias("x")).first()["x"]
    assert box == np.arange(48).reshape(3, 2, 4, 2).sum(axis=(1, 3)).ravel().tolist()
    cut = {(r["r"], r["c"]): r["pixels"] for r in raster.tile_patches(tiles, 6, 8, 3, 4).collect()}
    grid = np.arange(48).reshape(6, 8)
    assert cut == {(r, c): grid[3 * r : 3 * r + 3, 4 * c : 4 * c + 4].ravel().tolist() for r in (0, 1) for c in (0, 1)}
    base = spark.createDataFrame([(5, [0] * 1024)], "image_id long, payload array<int>")
    for k in (1, 16, 64):
        edited = base.select(raster.perturb_cells(F.col("payload"), F.col("image_id"), k).alias("x")).first()["x"]
        assert sum(v == 255 for v in edited) == k
    texts = spark.createDataFrame([(1, "abcdefg"), (2, ""), (3, None)], "k long, t string")
    assert sorted((r["image_id"], r["patch_no"], r["patch"]) for r in raster.text_patches(texts, "k", "t", 3).collect()) == [(1, 0, "abc"), (1, 1, "def"), (1, 2, "g")]
