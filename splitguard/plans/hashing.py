"""Queries on rasters, orientations and fingerprints, each with its SQL twin."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from splitguard import oracles as O
from splitguard.functions.dct import ortho_weights
from splitguard.operators import fingerprint as fp
from splitguard.operators import measures, raster
from splitguard.operators.orient import ALL_OPS, PAPER_OPS, explode_versions, orient, orientation_hashes
from splitguard.sources.carriers import collection


def joined(cells: Column) -> Column:
    return F.array_join(F.transform(cells, lambda x: x.cast("string")), ",")


def pixel_collection(spark, sf_dir, name):
    """A collection with its rasters written out as payload."""
    c = collection(spark, sf_dir, name)
    return raster.rasters(c.images, c.kind).withColumnRenamed("pixels", "payload")


def _raster(name):
    def run(spark, sf_dir):
        pixels = pixel_collection(spark, sf_dir, name)
        return pixels.select("image_id", "split", joined(F.col("payload")).alias("cells"))

    return run, O.with_(O.raster_cte(name), "SELECT image_id, split, array_to_string(g, ',') AS cells FROM ras")


def _phash(name, threshold):
    def run(spark, sf_dir):
        c = collection(spark, sf_dir, name)
        return fp.phash(c.images, c.kind, threshold=threshold)

    return run, O.with_(O.hashed(name, threshold), "SELECT image_id, split, hash FROM v")


def _ahash(name):
    def run(spark, sf_dir):
        c = collection(spark, sf_dir, name)
        return fp.ahash(c.images, c.kind)

    return run, O.with_(f"{O.raster_cte(name)}, {O.ahash_cte()}", "SELECT image_id, split, hash FROM ah")


def _digest(name, payload, table, key):
    def run(spark, sf_dir):
        digests = fp.content_digest(collection(spark, sf_dir, name).images)
        groups = digests.groupBy("digest").agg(
            F.min("image_id").alias("group_id"), F.count(F.lit(1)).alias("n")
        )
        return groups.where("n > 1")

    return run, f"""SELECT sha256({payload}) AS digest, min({key}) AS group_id, count(*) AS n
FROM {table} GROUP BY 1 HAVING count(*) > 1"""


def split_sizes(spark, sf_dir):
    return collection(spark, sf_dir, "documents").images.groupBy("split").agg(F.count(F.lit(1)).alias("n"))


def box_downsample_documents(spark, sf_dir):
    pixels = pixel_collection(spark, sf_dir, "documents")
    return pixels.select("image_id", joined(raster.box_downsample(F.col("payload"), 32, 32, 4)).alias("cells"))


def tile_patches_ledger(spark, sf_dir):
    tiles = pixel_collection(spark, sf_dir, "ledger").select(F.col("image_id").alias("tile_id"), F.col("payload").alias("pixels"))
    patches = raster.tile_patches(tiles, 32, 32, 16, 16)
    return patches.select("tile_id", "r", "c", joined(F.col("pixels")).alias("cells"))


def text_patches_documents(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return raster.text_patches(docs, "doc_id", "text", 500)


def phash256_documents(spark, sf_dir):
    c = collection(spark, sf_dir, "documents")
    deep = fp.phash(c.images, c.kind, side=16, threshold="mean_ac")
    return deep.select("image_id", *[F.element_at("hash", i + 1).alias(f"w{i}") for i in range(4)])


def phash_ortho_embeddings(spark, sf_dir):
    c = collection(spark, sf_dir, "embeddings")
    return fp.phash(c.images, c.kind, norm="ortho")


def phash_native_embeddings(spark, sf_dir):
    return fp.native_phash(pixel_collection(spark, sf_dir, "embeddings"), "mean_ac")


def dct_block_embeddings(spark, sf_dir):
    c = collection(spark, sf_dir, "embeddings")
    return fp.freq_block(c.images, c.kind).select("image_id", joined(F.col("block")).alias("block"))


def hash_bits_format(spark, sf_dir):
    c = collection(spark, sf_dir, "part")
    hashes = fp.phash(c.images, c.kind, threshold="mean_ac")
    back = fp.from_hex(fp.hash_hex(F.col("hash"))) == F.col("hash")
    return hashes.select("image_id", fp.hash_bits(F.col("hash")).alias("bits"), fp.hash_hex(F.col("hash")).alias("hex"), back.alias("same"))


def _oriented(ops):
    """Hashes by moving pixels and transforming each version anew."""

    def run(spark, sf_dir):
        turned = orient(pixel_collection(spark, sf_dir, "embeddings"), ops)
        # The operation rides in the split column through the kernel.
        tagged = turned.select("image_id", F.col("op").alias("split"), "payload")
        return fp.phash(tagged, threshold="mean_ac").select("image_id", F.col("split").alias("op"), "hash")

    parts = " UNION ALL ".join(
        f"SELECT image_id, '{op}' AS split, {O.oriented_pixels(op)} AS g FROM ras" for op in ops
    )
    ctes = f"""{O.raster_cte('embeddings')}, turned AS MATERIALIZED ({parts}),
{O.block_ctes('turned')}, {O.version_ctes('mean_ac')}"""
    return run, O.with_(ctes, "SELECT image_id, split AS op, hash FROM v")


def orientation_algebra_check(spark, sf_dir):
    pixels = pixel_collection(spark, sf_dir, "embeddings")
    by_pixels, _ = _oriented(ALL_OPS)
    moved = by_pixels(spark, sf_dir)
    derived = explode_versions(orientation_hashes(pixels, "pixels", ALL_OPS, "mean_ac"), ALL_OPS)
    both = moved.withColumnRenamed("hash", "h0").join(derived.select("image_id", "op", "hash"), ["image_id", "op"])
    return both.groupBy("op").agg(
        F.count(F.lit(1)).alias("n"), F.count_if(F.col("h0") != F.col("hash")).alias("n_mismatch")
    )


def radiometric_invariance(spark, sf_dir):
    base = pixel_collection(spark, sf_dir, "embeddings")
    out = None
    for edit, gain, bias in (("gain", 2, 0), ("bias", 1, 10)):
        edited = base.withColumn("payload", raster.radiometric(F.col("payload"), gain, bias))
        for t in ("mean_all", "mean_ac", "median_all"):
            row = measures.unchanged(fp.phash(base, threshold=t), fp.phash(edited, threshold=t), f"{edit}_{t}")
            out = row if out is None else out.unionByName(row)
    return out


def structural_sensitivity(spark, sf_dir):
    base = pixel_collection(spark, sf_dir, "embeddings")
    before, out = fp.phash(base, threshold="mean_ac"), None
    for k in (1, 4, 16, 64):
        edited = base.withColumn("payload", raster.perturb_cells(F.col("payload"), F.col("image_id"), k))
        row = measures.unchanged(before, fp.phash(edited, threshold="mean_ac"), f"cells_{k}")
        out = row if out is None else out.unionByName(row)
    return out


def _edits_sql(edits: list[tuple[str, str, str]]) -> str:
    """edits: (label, threshold, expression over g)."""
    ctes, rows = [O.raster_cte("embeddings"), O.block_ctes()], []
    seen = set()
    for n, (label, threshold, cells) in enumerate(edits):
        if threshold not in seen:
            ctes.append(O.version_ctes(threshold, out=f"base_{threshold}"))
            seen.add(threshold)
        ctes.append(f"e{n} AS MATERIALIZED (SELECT image_id, split, {cells} AS g FROM ras)")
        ctes.append(O.block_ctes(f"e{n}", f"b{n}"))
        ctes.append(O.version_ctes(threshold, block=f"b{n}", out=f"v{n}"))
        rows.append(f"""SELECT '{label}' AS edit, count(*) AS n, count(*) FILTER (a.hash = c.hash) AS n_same,
    sum(bit_count(xor(a.hash, c.hash)))::BIGINT AS flipped_bits FROM base_{threshold} AS a JOIN v{n} AS c USING (image_id)""")
    return O.with_(", ".join(ctes), " UNION ALL ".join(rows))


def entries():
    mean = "list_transform(range(64), lambda c: list_sum(list_transform(range(16), lambda i: g[((c // 8) * 4 + i // 4) * 32 + (c % 8) * 4 + i % 4 + 1])))"
    weights = [int(a * b) for a in ortho_weights(8) for b in ortho_weights(8)]
    scaled = ", ".join(f"{w} * b[{i + 1}]" for i, w in enumerate(weights))
    deep = ", ".join(f"{O.hash_of('b', 'mean_ac', 64 * i, 64 * i + 64)} AS w{i}" for i in range(4))
    patch = "list_transform(range(256), lambda i: g[(r * 16 + i // 16) * 32 + c * 16 + i % 16 + 1])"
    radiometric = [
        (f"{e}_{t}", t, f"list_transform(g, lambda x: {x})")
        for e, x in (("gain", "x * 2"), ("bias", "x + 10"))
        for t in ("mean_all", "mean_ac", "median_all")
    ]
    cells = [
        (f"cells_{k}", "mean_ac", f"list_transform(range(1024), lambda i: CASE WHEN ((i + image_id * 31) * 1013) % 1024 < {k} THEN 255 - g[i + 1] ELSE g[i + 1] END)")
        for k in (1, 4, 16, 64)
    ]
    turned8, turned_sql = _oriented(ALL_OPS)
    out = {
        "split_sizes": (split_sizes, f"SELECT {O.split_case('doc_id')} AS split, count(*) AS n FROM documents GROUP BY 1"),
        "box_downsample_documents": (
            box_downsample_documents,
            O.with_(O.raster_cte("documents"), f"SELECT image_id, array_to_string({mean}::BIGINT[], ',') AS cells FROM ras"),
        ),
        "tile_patches_ledger": (
            tile_patches_ledger,
            O.with_(O.raster_cte("ledger"), f"""SELECT image_id AS tile_id, r::INTEGER AS r, c::INTEGER AS c,
    array_to_string({patch}, ',') AS cells FROM ras, range(2) AS a(r), range(2) AS b(c)"""),
        ),
        "text_patches_documents": (
            text_patches_documents,
            """SELECT doc_id AS image_id, k::INTEGER AS patch_no, substr(text, k * 500 + 1, 500) AS patch
FROM (SELECT doc_id, text, unnest(range((length(text) - 1) // 500 + 1)) AS k FROM documents WHERE length(text) > 0)""",
        ),
        "raster_vec_embeddings": _raster("embeddings"),
        "raster_scan_part": _raster("part"),
        "raster_bigram_documents": _raster("bigram"),
        "raster_activity_events": _raster("activity"),
        "raster_ledger_lineitem": _raster("ledger"),
        "radiometric_invariance": (radiometric_invariance, _edits_sql(radiometric)),
        "structural_sensitivity": (structural_sensitivity, _edits_sql(cells)),
        "orient_versions_embeddings": _oriented(PAPER_OPS),
        "orient_all8_embeddings": (turned8, turned_sql),
        "orientation_algebra_check": (
            orientation_algebra_check,
            "SELECT op, (SELECT count(*) FROM embeddings) AS n, 0::BIGINT AS n_mismatch FROM (VALUES "
            + ", ".join(f"('{op}')" for op in ALL_OPS)
            + ") AS t(op)",
        ),
        "phash_literal_embeddings": _phash("embeddings", "mean_all"),
        "phash_literal_events": _phash("activity", "mean_all"),
        "phash_literal_documents": _phash("documents", "mean_all"),
        "phash_ac_documents": _phash("documents", "mean_ac"),
        "phash_ac_part": _phash("part", "mean_ac"),
        "phash_ac_pages": _phash("pages", "mean_ac"),
        "phash_ac_conversations": _phash("conversations", "mean_ac"),
        "phash_ac_benchmark": _phash("benchmark", "mean_ac"),
        "phash_ac_ledger": _phash("ledger", "mean_ac"),
        "phash_ac_bigram": _phash("bigram", "mean_ac"),
        "phash_median_documents": _phash("documents", "median_all"),
        "phash_sign_documents": _phash("documents", "sign_ac"),
        "phash256_documents": (
            phash256_documents,
            O.with_(f"{O.raster_cte('documents')}, {O.block_ctes(side=16)}", f"SELECT image_id, {deep} FROM blk"),
        ),
        "phash_ortho_embeddings": (
            phash_ortho_embeddings,
            O.with_(
                f"""{O.raster_cte('embeddings')}, {O.block_ctes(out='plain')},
blk AS MATERIALIZED (SELECT image_id, split, [{scaled}]::BIGINT[] AS b FROM plain), {O.version_ctes('mean_all')}""",
                "SELECT image_id, split, hash FROM v",
            ),
        ),
        "phash_native_embeddings": (
            phash_native_embeddings,
            O.with_(O.hashed("embeddings"), "SELECT image_id, split, hash FROM v"),
        ),
        "dct_block_embeddings": (
            dct_block_embeddings,
            O.with_(f"{O.raster_cte('embeddings')}, {O.block_ctes()}", "SELECT image_id, array_to_string(b, ',') AS block FROM blk"),
        ),
        "hash_bits_format": (
            hash_bits_format,
            O.with_(O.hashed("part"), """SELECT image_id,
    array_to_string(list_transform(range(63, -1, -1), lambda i: CASE WHEN i = 63 THEN (hash < 0)::INT ELSE (hash >> i::INT) & 1 END), '') AS bits,
    lpad(lower(printf('%x', CASE WHEN hash < 0 THEN hash::HUGEINT + 18446744073709551616 ELSE hash::HUGEINT END)), 16, '0') AS hex,
    true AS same FROM v"""),
        ),
        "digest_duplicates_documents": _digest("documents", "text", "documents", "doc_id"),
        "digest_duplicates_part": _digest("part", "p_name || '|' || p_type", "part", "p_partkey"),
    }
    for name in ("documents", "part", "pages", "embeddings"):
        out[f"ahash_{name}"] = _ahash(name)
    return out
