"""Time the headline queries; prints one JSON line.

BENCH_SF_DIR: table folder (default /root/testdata/sf0.1); BENCH_CPUS: local cores (default 8).
Each query is run once to warm up and then three times into a sink that keeps nothing; the
median counts. Rasters made from tables are 32 x 32 grey cells, so their milliseconds an image
are not comparable with decoding photographs. `images_300` and `images_650` are: colour PPM files of
the sizes of the published collections, generated into a temporary folder, are decoded, made grey,
fitted and hashed.
"""

from __future__ import annotations

import json
import os
import shutil
import tempfile
import time
from statistics import median

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from splitguard.functions.dct import PAPER_OPS
from splitguard.operators import collide, dedup
from splitguard.operators import fingerprint as fp
from splitguard.operators.orient import orient
from splitguard.plans import audits
from splitguard.plans.band_join import near_matches
from splitguard.plans.hashing import pixel_collection
from splitguard.operators.raster import fit_rasters
from splitguard.sources.carriers import collection
from splitguard.sources.files import read_rasters

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def timed(make, runs: int = 3) -> float:
    times = []
    for i in range(runs + 1):
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        if i:
            times.append(time.perf_counter() - began)
    return median(times)


IMAGES = {300: 400, 650: 120}  # side of the files -> how many


def make_images(base: str) -> None:
    rng = np.random.default_rng(7)
    for side, count in IMAGES.items():
        os.makedirs(f"{base}/{side}")
        for i in range(count):
            cells = rng.integers(0, 256, (side, side, 3), np.uint8)
            with open(f"{base}/{side}/{i}.ppm", "wb") as f:
                f.write(f"P6 {side} {side} 255\n".encode() + cells.tobytes())


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    docs, part = collection(spark, SF, "documents"), collection(spark, SF, "part")
    n_docs, n_part = docs.images.count(), part.images.count()

    def spread(c):  # a small table is one file; deal it over the cores once
        c.images.repartition(int(CPUS)).cache().count()
        return c.images.repartition(int(CPUS)).cache()

    docs_images, part_images = spread(docs), spread(part)
    six = fp.Hash("hashes", threshold="mean_ac", ops=PAPER_OPS)
    part_versions = fp.fingerprints(part_images, part.kind, six).cache()
    part_versions.count()
    train = part_versions.where("split = 'train'")
    val = part_versions.where("split = 'val'")
    pixels = pixel_collection(spark, SF, "embeddings").repartition(int(CPUS)).cache()
    pixels.count()
    vectors = audits.hashes(spark, SF, "embeddings", "sign_ac").cache()
    vectors.count()

    def six_pixel_paths():
        turned = orient(pixels).select("image_id", F.col("op").alias("split"), "payload")
        return fp.phash(turned, threshold="mean_ac")

    def nine_joins():
        out = None
        for s in audits.SPLITS:
            for t in audits.SPLITS:
                one = collide.overlap(
                    part_versions.where(F.col("split") == s), part_versions.where(F.col("split") == t), "aa"
                )
                out = one if out is None else out.unionByName(one)
        return out

    base = tempfile.mkdtemp(prefix="bench-images-")
    make_images(base)

    def image_path(side: int):
        read = read_rasters(spark, f"{base}/{side}")
        named = read.select(F.xxhash64("path").alias("image_id"), F.lit("train").alias("split"), "height", "width", "pixels")
        fitted = fit_rasters(named).select("image_id", "split", F.col("pixels").alias("payload"))
        return fp.phash(fitted, threshold="mean_ac")

    todo = {
        "images_300": lambda: image_path(300),
        "images_650": lambda: image_path(650),
        "overlap_augmented_uncached": lambda: audits.entries()["overlap_augmented_part"][0](spark, SF),
        "hash_documents": lambda: fp.phash(docs_images, docs.kind, threshold="mean_ac"),
        "hash_part": lambda: fp.phash(part_images, part.kind, threshold="mean_ac"),
        "ahash_documents": lambda: fp.ahash(docs_images, docs.kind),
        "hash_native_embeddings": lambda: fp.native_phash(pixels, "mean_ac"),
        "six_orientations_one_block": lambda: fp.fingerprints(pixels, "pixels", six),
        "six_orientations_by_pixels": six_pixel_paths,
        "lookup_val_in_train": lambda: collide.overlap(val, train, "oo"),
        "matrix_one_pass": lambda: collide.overlap_matrix(part_versions, audits.SPLITS, "aa"),
        "matrix_nine_joins": nine_joins,
        "dedup_first_seen": lambda: dedup.retain_unique(part_versions),
        "dedup_components": lambda: dedup.retain_unique(part_versions, "components"),
        "sanitize_part": lambda: dedup.sanitize(part_versions)[1],
        "near_band_join": lambda: near_matches(vectors, vectors, 4),
        "near_brute_force": lambda: collide.brute_force_pairs(vectors, vectors, 4),
        "lineitem_part_leakage": lambda: audits.lineitem_part_leakage(spark, SF),
    }
    took = {name: round(timed(make), 4) for name, make in todo.items()}
    shutil.rmtree(base)
    counts = {r["split"]: r["n"] for r in part_versions.groupBy("split").agg(F.count("*").alias("n")).collect()}
    print(
        json.dumps(
            {
                "metric": "headline queries, sum of medians",
                "value": round(sum(took.values()), 3),
                "unit": "sec",
                "queries": took,
                "sf": os.path.basename(SF.rstrip("/")),
                "cpus": int(CPUS),
                "ms_per_image": {
                    "hash_documents": round(1000 * took["hash_documents"] / n_docs, 4),
                    "hash_part": round(1000 * took["hash_part"] / n_part, 4),
                    **{f"images_{s}": round(1000 * took[f"images_{s}"] / n, 4) for s, n in IMAGES.items()},
                },
                "ms_per_lookup": round(1000 * took["lookup_val_in_train"] / counts["val"], 5),
                "paper_ms_per_image": 4.0,
                "paper_ms_per_lookup": 4.0,
            }
        )
    )


if __name__ == "__main__":
    main()
