"""Measures: agreement, precision, recall, invariance, sensitivity, health and cost."""

from __future__ import annotations

import time
from collections.abc import Iterator
from itertools import product

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from splitguard.functions.dct import SIDE
from splitguard.functions.runtime import join_by_key, reliable
from splitguard.operators.collide import overlap_matrix
from splitguard.operators.fingerprint import ROWS, hamming
from splitguard.operators.raster import RASTERISERS, SPLITS


def compare_hashes(both: DataFrame, splits: tuple[str, ...] = SPLITS) -> DataFrame:
    """(search, target, n_search, phash_hits, ahash_hits, phash_pct, ahash_pct) per ordered pair.

    both is (image_id, split, phash, ahash).
    """

    def table(name: str) -> DataFrame:
        one = both.select("image_id", "split", F.array(name).alias("hashes"))
        return overlap_matrix(one, list(splits)).select(
            "search", "target", "n_search", F.col("n_hits").alias(f"{name}_hits"),
            F.col("overlap_pct").alias(f"{name}_pct"),
        )

    return table("phash").join(table("ahash").drop("n_search"), ["search", "target"])


def flagged(hashed: DataFrame, search: str, target: str) -> DataFrame:
    """(image_id) of the search split whose hash is in the target split; hashed has column hash."""
    index = hashed.where(F.col("split") == target).select("hash").distinct()
    return hashed.where(F.col("split") == search).join(index, "hash", "left_semi").select("image_id")


def hash_agreement(both: DataFrame, splits: tuple[str, ...] = SPLITS) -> DataFrame:
    """(search, target, n_both, n_phash_only, n_ahash_only) over ordered pairs of different splits."""
    marked = reliable(both.select("image_id", "split", "phash", "ahash"))
    flags = []
    for name in ("phash", "ahash"):
        held = marked.where(F.col(name).isNotNull()).groupBy(name).agg(
            *[F.max(F.col("split") == s).alias(f"{name}_{s}") for s in splits], F.count(F.lit(1)).alias("n")
        )
        marked = join_by_key(marked, reliable(held), [name], how="left")
        flags += [f"{name}_{s}" for s in splits]
    marked = marked.select("split", *[F.coalesce(f, F.lit(False)).alias(f) for f in flags])
    cells = []
    for s, t in product(splits, repeat=2):
        if s == t:
            continue
        own = F.col("split") == s
        p, a = F.col(f"phash_{t}"), F.col(f"ahash_{t}")
        cells.append(
            F.struct(
                F.lit(s).alias("search"), F.lit(t).alias("target"),
                F.count_if(own & p & a).alias("n_both"), F.count_if(own & p & ~a).alias("n_phash_only"),
                F.count_if(own & ~p & a).alias("n_ahash_only"),
            )
        )
    return marked.agg(F.array(*cells).alias("cells")).select(F.inline("cells"))


def collision_precision(hashed: DataFrame, digests: DataFrame) -> DataFrame:
    """(n_flagged, n_false, n_exact, precision) over a whole collection.

    An image is flagged if its hash occurs twice or more; it is a false positive if its
    content occurs once. hashed is (image_id, hash), digests (image_id, digest).
    """
    joined = hashed.select("image_id", "hash").join(digests.select("image_id", "digest"), "image_id")
    by_hash = joined.groupBy("hash", "digest").agg(F.count(F.lit(1)).alias("n"))
    sums = by_hash.groupBy("hash").agg(
        F.sum("n").alias("members"), F.sum(F.when(F.col("n") == 1, 1).otherwise(0)).alias("alone"),
        F.sum(F.when(F.col("n") > 1, F.col("n")).otherwise(0)).alias("copies"),
    )
    hit = (F.col("members") > 1) & F.col("hash").isNotNull()
    made = sums.agg(
        F.coalesce(F.sum(F.when(hit, F.col("members"))), F.lit(0)).alias("n_flagged"),
        F.coalesce(F.sum(F.when(hit, F.col("alone"))), F.lit(0)).alias("n_false"),
        F.coalesce(F.sum(F.when(hit, F.col("copies"))), F.lit(0)).alias("n_exact"),
    )
    share = F.when(F.col("n_flagged") > 0, F.col("n_exact") / F.col("n_flagged"))
    return made.withColumn("precision", share)


def verify_pairs(pairs: DataFrame, pixels: DataFrame) -> DataFrame:
    """(id_a, id_b, sum_abs_diff, mean_abs_diff) of pairs (id_a, id_b), from (image_id, pixels)."""
    a = pixels.select(F.col("image_id").alias("id_a"), F.col("pixels").alias("pa"))
    b = pixels.select(F.col("image_id").alias("id_b"), F.col("pixels").alias("pb"))
    both = _beside(pairs, a, b)
    total = F.aggregate(
        F.zip_with("pa", "pb", lambda x, y: F.abs(x - y)), F.lit(0).cast("long"), lambda s, x: s + x
    )
    return both.select(
        "id_a", "id_b", total.alias("sum_abs_diff"), (total / F.size("pa")).alias("mean_abs_diff")
    )


def _beside(pairs: DataFrame, a: DataFrame, b: DataFrame) -> DataFrame:
    """pairs (id_a, id_b) with the columns of both images.

    Spark takes rasters and texts for much smaller than they are, so the sides are merged and never
    broadcast, but for those of images in very many pairs: they are sent to the pairs, not they to them.
    """
    pairs = reliable(pairs.select("id_a", "id_b"))
    held = pairs.groupBy("id_a").agg(F.count(F.lit(1)).alias("n"))
    used = a.hint("merge").join(held, "id_a").hint("merge")
    return join_by_key(pairs.join(b.hint("merge"), "id_b"), used, ["id_a"], most_hot=2_000)


def verify_payloads(pairs: DataFrame, images: DataFrame, kind: str) -> DataFrame:
    """verify_pairs from a collection (image_id, split, payload): payloads are shuffled, and rasters
    made of them a batch at a time. Without a payload there is no difference."""
    make = RASTERISERS[kind]
    sides = [images.select(F.col("image_id").alias(f"id_{x}"), F.col("payload").alias(f"p{x}")) for x in "ab"]

    def cells(part: pa.RecordBatch, side: str):
        _, first, back = np.unique(part.column(f"id_{side}").to_numpy(), return_index=True, return_inverse=True)
        return make(part.column(f"p{side}").take(pa.array(first)))[back]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = pc.and_(batch.column("pa").is_valid(), batch.column("pb").is_valid())
            whole, holes = batch.filter(good), batch.filter(pc.invert(good))
            found = []
            for part in (whole.slice(i, ROWS) for i in range(0, whole.num_rows, ROWS)):
                apart = np.abs(cells(part, "a") - cells(part, "b")).sum(axis=(1, 2))
                found.append((part, pa.array(apart, pa.int64()), pa.array(apart / SIDE**2)))
            if holes.num_rows:
                found.append((holes, pa.nulls(holes.num_rows, pa.int64()), pa.nulls(holes.num_rows, pa.float64())))
            for p, total, mean in found:
                yield pa.RecordBatch.from_arrays(
                    [p.column("id_a"), p.column("id_b"), total, mean],
                    names=["id_a", "id_b", "sum_abs_diff", "mean_abs_diff"],
                )

    both = _beside(pairs, *sides).select("id_a", "id_b", "pa", "pb")
    return both.mapInArrow(kernel, "id_a long, id_b long, sum_abs_diff long, mean_abs_diff double")


def unchanged(before: DataFrame, after: DataFrame, label: str) -> DataFrame:
    """(edit, n, n_same, flipped_bits) of hashes (image_id, hash) before and after an edit."""
    both = before.select("image_id", F.col("hash").alias("h0")).join(
        after.select("image_id", F.col("hash").alias("h1")), "image_id"
    )
    flips = hamming(F.col("h0"), F.col("h1"))
    return both.agg(
        F.lit(label).alias("edit"), F.count(F.lit(1)).alias("n"),
        F.count_if(F.col("h0") == F.col("h1")).alias("n_same"),
        F.coalesce(F.sum(flips), F.lit(0)).cast("long").alias("flipped_bits"),
    )


def hash_health(hashed: DataFrame) -> DataFrame:
    """(bit, n, n_set) for each of 64 bits of (image_id, hash): shows a collapsed threshold."""
    bits = F.transform(
        F.sequence(F.lit(0), F.lit(63)),
        lambda i: F.struct(i.alias("bit"), F.getbit("hash", i).cast("long").alias("is_set")),
    )
    return hashed.select(F.inline(bits)).groupBy("bit").agg(
        F.count(F.lit(1)).alias("n"), F.sum("is_set").alias("n_set")
    )


def raster_stats(pixels: Column) -> Column:
    """struct(contrast, zero_cells) of an array of cells."""
    return F.struct(
        (F.array_max(pixels) - F.array_min(pixels)).alias("contrast"),
        F.size(F.filter(pixels, lambda g: g == 0)).alias("zero_cells"),
    )


def flat_audit(hashed: DataFrame, pixels: DataFrame) -> DataFrame:
    """(collided, n, sum_contrast, min_contrast, sum_zero_cells): how flat collided images are."""
    sizes = hashed.where("hash is not null").groupBy("hash").agg(F.count(F.lit(1)).alias("members"))
    stats = pixels.select("image_id", raster_stats(F.col("pixels")).alias("s"))
    joined = hashed.select("image_id", "hash").join(sizes, "hash", "left").join(stats, "image_id")
    return joined.groupBy((F.coalesce("members", F.lit(1)) > 1).alias("collided")).agg(
        F.count(F.lit(1)).alias("n"), F.sum("s.contrast").alias("sum_contrast"),
        F.min("s.contrast").alias("min_contrast"), F.sum("s.zero_cells").alias("sum_zero_cells"),
    )


def depth_ablation(deep: DataFrame, depths: dict[str, str]) -> DataFrame:
    """(depth, n, n_redundant): copies that each depth sees; depths maps a label to a column."""
    out = None
    for label, column in depths.items():
        groups = deep.groupBy(F.col(column).alias("h")).agg(F.count(F.lit(1)).alias("n"))
        row = groups.agg(
            F.lit(label).alias("depth"), F.coalesce(F.sum("n"), F.lit(0)).alias("n"),
            F.coalesce(F.sum(F.col("n") - 1), F.lit(0)).alias("n_redundant"),
        )
        out = row if out is None else out.unionByName(row)
    return out


def label_agreement(hashed: DataFrame, labels: DataFrame) -> DataFrame:
    """(n_groups, n_members, n_agreeing): groups of equal hashes whose labels are all alike."""
    joined = hashed.select("image_id", "hash").where("hash is not null").join(labels, "image_id")
    groups = joined.groupBy("hash").agg(
        F.count(F.lit(1)).alias("n"), F.min("label").alias("low"), F.max("label").alias("high")
    ).where("n > 1")
    return groups.agg(
        F.count(F.lit(1)).alias("n_groups"), F.coalesce(F.sum("n"), F.lit(0)).alias("n_members"),
        F.count_if(F.col("low") == F.col("high")).alias("n_agreeing"),
    )


def memorization_gap(hashed: DataFrame, labels: DataFrame) -> DataFrame:
    """(leaked, n, n_right, accuracy) of a predictor that copies the label of the least train twin.

    An evaluation image without a twin gets the commoner label of train. hashed is
    (image_id, split, hash), labels (image_id, label of 0 or 1).
    """
    joined = hashed.join(labels, "image_id")
    train = joined.where("split = 'train'")
    twin = train.groupBy("hash").agg(F.min_by("label", "image_id").alias("twin_label"))
    common = train.agg((2 * F.sum("label") >= F.count(F.lit(1))).cast("int").alias("common_label"))
    rest = joined.where("split != 'train'").join(twin, "hash", "left").join(F.broadcast(common), how="left")
    guess = F.coalesce("twin_label", "common_label")
    return rest.groupBy(F.col("twin_label").isNotNull().alias("leaked")).agg(
        F.count(F.lit(1)).alias("n"), F.count_if(guess == F.col("label")).alias("n_right")
    ).withColumn("accuracy", F.col("n_right") / F.col("n"))


def planted_copies(images: DataFrame, ops: tuple[str, ...]) -> DataFrame:
    """(image_id, split, payload, source_id, op): every raster reoriented by every operation, in the
    next split; image_id is -1 less a number of its own."""
    from splitguard.operators.orient import orient

    following = F.create_map(*[F.lit(x) for x in ("train", "val", "val", "test", "test", "train")])
    nth = F.array_position(F.array(*[F.lit(op) for op in ops]), F.col("op")) - 1
    return orient(images, ops).select(
        (-1 - (F.col("image_id") * len(ops) + nth)).alias("image_id"), following[F.col("split")].alias("split"),
        "payload", F.col("image_id").alias("source_id"), "op",
    )


def index_size(hashed: DataFrame) -> DataFrame:
    """(n_images, n_versions, n_keys, bytes_an_image, bytes_a_key) of (image_id, hashes): 8 bytes a
    version kept with an image; a key of the index holds hash, least image and count, 24 bytes."""
    versions = hashed.select("image_id", F.explode("hashes").alias("hash")).where("hash is not null")
    keys = versions.groupBy("hash").agg(F.count(F.lit(1)).alias("n"))
    made = keys.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_versions"), F.count(F.lit(1)).alias("n_keys"))
    images = hashed.agg(F.count(F.lit(1)).alias("n_images"))
    return images.join(made, how="left").select(  # two rows of counts
        "n_images", "n_versions", "n_keys",
        (8 * F.col("n_versions") / F.when(F.col("n_images") > 0, F.col("n_images"))).alias("bytes_an_image"),
        F.lit(24).alias("bytes_a_key"),
    )


def planted_recall(copies: DataFrame, originals: DataFrame) -> DataFrame:
    """(op, n, found_oo, found_oa, found_aa) of copies (source_id, op, hashes) in their originals."""
    pairs = copies.select("source_id", "op", F.col("hashes").alias("c")).join(
        originals.select(F.col("image_id").alias("source_id"), F.col("hashes").alias("o")), "source_id"
    )
    first = F.element_at("c", 1)
    return pairs.groupBy("op").agg(
        F.count(F.lit(1)).alias("n"),
        F.count_if(first == F.element_at("o", 1)).alias("found_oo"),
        F.count_if(F.array_contains("o", first)).alias("found_oa"),
        F.count_if(F.arrays_overlap("c", "o")).alias("found_aa"),
    )


def cost_report(spark: SparkSession, stages: dict[str, tuple[DataFrame, int]]) -> list[dict]:
    """Wall milliseconds an item of each stage, run into a sink that keeps nothing."""
    out = []
    for name, (df, items) in stages.items():
        began = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        took = time.perf_counter() - began
        out.append({"stage": name, "items": items, "seconds": took, "ms_per_item": 1000 * took / max(1, items)})
    return out


