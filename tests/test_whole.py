"""Images without a fingerprint, one kernel a collection, whole texts and rasters by size."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from splitguard.functions import runtime
from splitguard.functions.dct import factor_block
from splitguard.operators import collide, dedup, measures, raster
from splitguard.operators import fingerprint as fp
from splitguard.plans import audits

SF = "/root/testdata/sf0.001"
SCHEMA = "image_id long, split string, hashes array<long>"
ROWS = [(1, "train", None), (2, "train", None), (3, "val", None), (4, "val", [7, 8]), (5, "train", [7, 9]), (6, "train", [7, 9])]


def test_images_without_a_fingerprint(spark):
    v = spark.createDataFrame(ROWS, SCHEMA)
    train, val = v.where("split = 'train'"), v.where("split = 'val'")
    for sides in ("oo", "oa", "ao", "aa"):
        cells = {(r["search"], r["target"]): (r["n_search"], r["n_hits"]) for r in collide.overlap_matrix(v, ["train", "val"], sides).collect()}
        for s, t, a, b in (("train", "val", train, val), ("val", "train", val, train)):
            one = collide.overlap(a, b, sides).first()
            assert cells[s, t] == (one["n_search"], one["n_hits"])
        assert cells["val", "train"] == ((3, 1) if sides[0] == "a" else (2, 1))
    h = v.select("image_id", "split", F.element_at("hashes", 1).alias("hash"))
    assert tuple(collide.self_overlap(h).first())[:2] == (6, 2)
    assert collide.self_overlap(h, "members").first()["n_hits"] == 3
    assert collide.hash_index(h).count() == 1
    assert [tuple(r) for r in dedup.group_size_histogram(h).collect()] == [(3, 1, 3)]
    assert sorted(r["image_id"] for r in dedup.duplicate_groups(h).collect()) == [4, 5, 6]
    for policy in dedup.POLICIES:
        kept = sorted(r["image_id"] for r in dedup.retain_unique(v, policy).collect())
        assert kept == [1, 2, 3, 4, 5]
    clean, report = dedup.sanitize(v)
    assert sorted(r["image_id"] for r in clean.collect()) == [1, 2, 3, 4]
    both = h.select("image_id", "split", F.col("hash").alias("phash"), F.col("hash").alias("ahash"))
    agreed = {(r["search"], r["target"]): r["n_both"] for r in measures.hash_agreement(both, ("train", "val")).collect()}
    assert agreed == {("train", "val"): 2, ("val", "train"): 1}
    assert measures.index_size(v).first()["n_versions"] == 6


@pytest.mark.parametrize("make", ["overlap_augmented_part", "hash_agreement_part", "near_matches_tau4_embeddings", "dedup_augmented_part", "memorization_gap_documents"])
def test_a_payload_is_hashed_once(spark, make):
    """Fingerprints are a narrow checkpointed table, so no kernel is left in the plan of the result."""
    plan = audits.entries()[make][0](spark, SF)._jdf.queryExecution().toString()
    assert "MapInArrow" not in plan and "Scan ExistingRDD" in plan


def test_every_byte_of_a_long_text_counts():
    text = "a" * 100_000
    cells = raster.scan_rasters(pa.array([text, text[:50_010] + "z" * 40 + text[50_050:]]))
    assert (cells[0] == 4 * ord("a")).all() and (cells[1] != cells[0]).any()
    rng = np.random.default_rng(2)
    data = rng.integers(32, 127, 9001).astype(np.uint8)
    edges = np.arange(4097) * 9001 >> 12
    pixels = np.array([data[a:b].sum() // (b - a) for a, b in zip(edges, edges[1:])]).reshape(64, 64)
    want = pixels.reshape(32, 2, 32, 2).sum(axis=(1, 3))
    assert (raster.scan_rasters(pa.array([data.tobytes().decode()]))[0] == want).all()


def test_rasters_by_size_are_those_one_by_one(spark):
    rng = np.random.default_rng(1)
    rows = []
    for i, (h, w) in enumerate([(32, 32), (40, 33), (40, 33), (300, 300), (31, 40), (64, 48)]):
        rows.append((i, "train", h, w, rng.integers(0, 256, h * w).tolist()))
    rows += [(6, "val", 40, 33, [1] * 5), (7, "val", None, 33, [1]), (8, "val", 33, 33, None), (9, "val", 33, 33, [None] + [1] * 1088)]
    images = spark.createDataFrame(rows, "image_id long, split string, height int, width int, pixels array<int>").repartition(2)
    fitted = {r["image_id"]: r for r in raster.fit_rasters(images).collect()}
    hashed = {r["image_id"]: r["hash"] for r in fp.phash_factor(images, 2).collect()}
    for i, _, h, w, p in rows[:6]:
        grey = np.array(p).reshape(h, w)
        assert fitted[i]["pixels"] == (None if h < 32 else raster.fit_array(grey).ravel().tolist())
        block = factor_block(grey, 2)
        bits = 64 * block > block.sum()
        want = sum(1 << k for k in range(64) if bits[k])
        assert hashed[i] % (1 << 64) == want
    reasons = [fitted[i]["reason"] for i in (4, 6, 7, 8, 9)]
    assert reasons == ["smaller than the target", "pixels do not fill the raster", "no pixels", "no pixels", "null pixel"]
    assert all(fitted[i]["pixels"] is None and hashed[i] is None for i in (6, 7, 8, 9))
    with pytest.raises(Exception, match="no pixels|smaller than the target|do not fill|null pixel"):
        raster.fit_rasters(images, on_bad="raise").collect()


def test_search_in_blocks(spark, monkeypatch):
    h = runtime.reliable(spark.range(300).select(F.col("id").alias("image_id"), F.xxhash64("id").alias("hash")))
    queries = h.where("image_id % 20 = 0")
    whole = sorted(collide.hamming_search(queries, h, 20).collect())
    monkeypatch.setattr(collide, "BLOCK_QUERIES", 8)
    assert sorted(collide.hamming_search(queries, h, 20).collect()) == whole and len(whole) > 15


def test_a_cluster_needs_a_shared_folder():
    class Far:
        master = "spark://somewhere:7077"

        def getCheckpointDir(self):
            return None

    class Unset:
        def get(self, name, default):
            return default

    class Session:
        sparkContext, conf = Far(), Unset()

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        runtime.ensure_checkpoint_dir(Session())
