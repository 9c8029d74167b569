"""Queries on overlap, de-duplication, leakage and their measures, each with its SQL twin."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from splitguard import oracles as O
from splitguard.functions.dct import ALL_OPS, PAPER_OPS
from splitguard.functions.runtime import ensure_checkpoint_dir, join_by_key, reliable
from splitguard.operators import collide, dedup, galleries, measures, raster
from splitguard.operators import fingerprint as fp
from splitguard.plans.band_join import near_hashes
from splitguard.plans.hashing import pixel_collection
from splitguard.sources.carriers import collection, table

SPLITS = list(raster.SPLITS)


def hashes(spark, sf_dir, name, threshold="mean_ac") -> DataFrame:
    """(image_id, split, hash): a checkpointed table, so that a payload is read and hashed once."""
    c = collection(spark, sf_dir, name)
    return reliable(fp.phash(c.images, c.kind, threshold=threshold))


def versions(spark, sf_dir, name, ops=PAPER_OPS, threshold="mean_ac") -> DataFrame:
    """(image_id, split, hashes), checkpointed."""
    c = collection(spark, sf_dir, name)
    return reliable(fp.fingerprints(c.images, c.kind, fp.Hash("hashes", threshold=threshold, ops=tuple(ops))))


def two_hashes(spark, sf_dir, name) -> DataFrame:
    c = collection(spark, sf_dir, name)
    return reliable(
        fp.fingerprints(c.images, c.kind, fp.Hash("phash", threshold="mean_ac"), fp.Hash("ahash", kind="ahash"))
    )


def _part(df: DataFrame, split: str) -> DataFrame:
    return df.where(F.col("split") == split)


# ---- overlap ------------------------------------------------------------------------


def _official(name):
    def run(spark, sf_dir):
        return collide.overlap_matrix(versions(spark, sf_dir, name, ("id",)), SPLITS, "oo")

    return run, O.with_(O.hashed(name), O.matrix("v", "v", "oo", False))


def _augmented(name):
    def run(spark, sf_dir):
        return collide.overlap_matrix(versions(spark, sf_dir, name), SPLITS, "aa")

    return run, O.with_(f"{O.hashed(name, ops=PAPER_OPS)}, {O.kept_cte()}", O.matrix("v", "v", "aa", True))


def _one_way(search, target, sides, name="part"):
    def run(spark, sf_dir):
        v = versions(spark, sf_dir, name)
        return collide.overlap(_part(v, search), _part(v, target), sides)

    s = "" if sides[0] == "a" else " AND nth = 0"
    t = "" if sides[1] == "a" else " AND nth = 0"
    return run, O.with_(O.hashed(name, ops=PAPER_OPS), f"""SELECT count(*) AS n_search,
    count(*) FILTER (hash IN (SELECT hash FROM v WHERE split = '{target}'{t})) AS n_hits,
    100.0::DOUBLE * count(*) FILTER (hash IN (SELECT hash FROM v WHERE split = '{target}'{t})) / count(*) AS overlap_pct
FROM v WHERE split = '{search}'{s}""")


def overlap_matrix_part_full(spark, sf_dir):
    v = versions(spark, sf_dir, "part")
    return collide.overlap_matrix(v, SPLITS, "oo").unionByName(collide.overlap_matrix(v, SPLITS, "aa"))


def _self(count):
    def run(spark, sf_dir):
        return collide.self_overlap(hashes(spark, sf_dir, "part"), count)

    extra = "n - 1" if count == "redundant" else "CASE WHEN n > 1 THEN n ELSE 0 END"
    return run, O.with_(O.hashed("part"), f"""SELECT sum(n)::BIGINT AS n_search, sum({extra})::BIGINT AS n_hits,
    100.0::DOUBLE * sum({extra}) / sum(n) AS overlap_pct FROM (SELECT count(*) AS n FROM v GROUP BY hash)""")


def _self_augmented(policy):
    def run(spark, sf_dir):
        ops = ALL_OPS if policy == "canonical" else PAPER_OPS
        v = versions(spark, sf_dir, "part", ops).withColumn("split", F.lit("all"))
        n = v.agg(F.count(F.lit(1)).alias("n_search"))
        kept = dedup.retain_unique(v, policy).agg(F.count(F.lit(1)).alias("kept"))
        both = n.join(kept, how="left")  # two rows of one count
        return both.select("n_search", (F.col("n_search") - F.col("kept")).alias("n_hits"))

    return run


def lookup_one(spark, sf_dir):
    h = hashes(spark, sf_dir, "documents")
    return collide.lookup(h.where("image_id = 1"), collide.hash_index(h.where("image_id <> 1")))


def hash_index_documents(spark, sf_dir):
    return collide.hash_index(hashes(spark, sf_dir, "documents"))


def overlap_pages_documents(spark, sf_dir):
    pages, docs = (versions(spark, sf_dir, n, ("id",)) for n in ("pages", "documents"))
    return collide.overlap(pages, docs, "oo")


def benchmark_in_documents(spark, sf_dir):
    """Items whose whole text stands in a document, found by the hash of the passage's own patch."""
    items = hashes(spark, sf_dir, "benchmark").select("image_id", "hash")
    docs = hashes(spark, sf_dir, "documents").select("hash").distinct()
    hit = items.join(docs, "hash", "left_semi").agg(F.count(F.lit(1)).alias("n_hash_hits"))
    total = items.agg(F.count(F.lit(1)).alias("n_items"))
    return total.join(hit, how="left")  # two rows of one count


def benchmark_patch_recall(spark, sf_dir):
    """Share of items met by text patches of 200 characters: patches are not aligned with passages."""
    docs = raster.text_patches(table(spark, sf_dir, "documents"), "doc_id", "text", 200)
    items = raster.text_patches(table(spark, sf_dir, "benchmark"), "item_id", "text", 200)

    def hashed(patches):
        slim = patches.select("image_id", F.lit("-").alias("split"), F.col("patch").alias("payload"))
        return fp.phash(slim, "text", threshold="mean_ac")

    wanted = hashed(items)
    found = wanted.join(hashed(docs).select("hash").distinct(), "hash", "left_semi")
    n = wanted.agg(F.count_distinct("image_id").alias("n_items"), F.count(F.lit(1)).alias("n_patches"))
    hits = found.agg(F.count_distinct("image_id").alias("n_items_hit"), F.count(F.lit(1)).alias("n_patches_hit"))
    return n.join(hits, how="left")  # two rows of counts


def near_matches_tau2_part(spark, sf_dir):
    h = hashes(spark, sf_dir, "part")
    return near_hashes(h, h, 2).where("hash_a < hash_b")


def near_matches_tau4_embeddings(spark, sf_dir):
    """Near hashes with their groups: members are those of the index."""
    h = hashes(spark, sf_dir, "embeddings", "sign_ac")
    index = reliable(collide.hash_index(h))
    near = near_hashes(h, h, 4).where("hash_a < hash_b")
    for side in ("a", "b"):
        own = index.select(F.col("hash").alias(f"hash_{side}"), F.col("min_id").alias(f"min_{side}"), F.col("n").alias(f"n_{side}"))
        near = near.join(own, f"hash_{side}")
    return near


def hamming_pairs_brute_embeddings(spark, sf_dir):
    h = hashes(spark, sf_dir, "embeddings", "sign_ac")
    return collide.brute_force_pairs(h, h, 16)


def lineitem_part_leakage(spark, sf_dir):
    """Rows of orders before and after a date as splits: part rasters that leak from one to the other."""
    h = hashes(spark, sf_dir, "part").select(F.col("image_id").alias("l_partkey"), "hash")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_orderdate")
    late = F.col("o_orderdate") >= F.lit("1997-01-01").cast("timestamp_ntz")
    rows = lines.join(orders, "l_orderkey").join(h, "l_partkey").select("hash", late.alias("late"))
    counted = rows.groupBy("hash").agg(F.count_if("late").alias("late"), F.count_if(~F.col("late")).alias("early"))
    return counted.agg(
        F.sum("late").alias("n_search"), F.sum(F.when(F.col("early") > 0, F.col("late")).otherwise(0)).alias("n_hits")
    )


def tile_patch_overlap_ledger(spark, sf_dir):
    """Ledger tiles cut into 16 x 16 patches, grown to 32 x 32 and compared across splits."""
    tiles = pixel_collection(spark, sf_dir, "ledger").select(F.col("image_id").alias("tile_id"), F.col("payload").alias("pixels"))
    cut = raster.tile_patches(tiles, 32, 32, 16, 16)
    grown = F.transform(
        F.sequence(F.lit(0), F.lit(1023)),
        lambda i: F.element_at("pixels", (F.floor(i / 64) * 16 + F.floor(F.pmod(i, F.lit(32)) / 2) + 1).cast("int")),
    )
    images = cut.select(
        (F.col("tile_id") * 4 + F.col("r") * 2 + F.col("c")).alias("image_id"),
        raster.split_of(F.col("tile_id")).alias("split"),
        grown.alias("payload"),
    )
    v = fp.fingerprints(images, "pixels", fp.Hash("hashes", threshold="mean_ac", ops=("id",)))
    return collide.overlap_matrix(v, SPLITS, "oo")


# ---- de-duplication and leakage -----------------------------------------------------


def _dedup(name, ops, policy):
    def run(spark, sf_dir):
        return dedup.retain_unique(versions(spark, sf_dir, name, ops), policy).select("image_id", "split")

    return run


def duplicate_groups_documents(spark, sf_dir):
    return dedup.duplicate_groups(hashes(spark, sf_dir, "documents"))


def group_size_histogram_part(spark, sf_dir):
    return dedup.group_size_histogram(hashes(spark, sf_dir, "part"))


def _remove(name):
    def run(spark, sf_dir):
        v = dedup.retain_unique(versions(spark, sf_dir, name).where("split <> 'test'"))
        v = reliable(v)
        return dedup.remove_leakage(_part(v, "train"), _part(v, "val")).select("image_id")

    return run


_FINAL = """leak AS (SELECT DISTINCT image_id FROM v JOIN kept USING (image_id, split) WHERE split = 'train'
    AND hash IN (SELECT hash FROM v JOIN kept USING (image_id, split) WHERE split = 'val'))"""


def sanitize_report(spark: SparkSession, sf_dir: str, name: str, priority=("val", "train")) -> DataFrame:
    return dedup.sanitize(versions(spark, sf_dir, name), priority=priority)[1]


def _sanitize(name):
    def run(spark, sf_dir):
        return sanitize_report(spark, sf_dir, name)

    return run, O.with_(f"{O.hashed(name, ops=PAPER_OPS)}, {O.kept_cte()}, {_FINAL}", """
SELECT s AS split, (SELECT count(DISTINCT image_id) FROM v WHERE split = s) AS n_official,
    (SELECT count(*) FROM kept WHERE split = s) AS n_unique,
    (SELECT count(*) FROM kept WHERE split = s) - CASE WHEN s = 'train' THEN (SELECT count(*) FROM leak) ELSE 0 END AS n_final
FROM (VALUES ('train'), ('val')) AS t(s)""")


def sanitize_three_way_part(spark, sf_dir):
    return sanitize_report(spark, sf_dir, "part", ("test", "val", "train"))


def leak_pairs_documents(spark, sf_dir):
    h = hashes(spark, sf_dir, "documents")
    return dedup.leak_pairs(_part(h, "train"), _part(h, "val"))


def leak_members_documents(spark, sf_dir):
    h = hashes(spark, sf_dir, "documents")
    return dedup.leak_members(_part(h, "train"), _part(h, "val"))


def write_clean_part(spark, sf_dir):
    """Cleaned splits written as Parquet and read again: (split, n, n_hashes)."""
    path = f"{ensure_checkpoint_dir(spark)}/clean-{uuid.uuid4().hex}"
    dedup.write_clean(dedup.sanitize(versions(spark, sf_dir, "part"))[0], path)
    back = spark.read.parquet(path)
    return back.groupBy("split").agg(F.count(F.lit(1)).alias("n"), F.sum(F.size("hashes")).alias("n_versions"))


# ---- images without a fingerprint -------------------------------------------------------


def _unreadable(spark, sf_dir):
    """Versions of part, every tenth image without any."""
    return versions(spark, sf_dir, "part").withColumn("hashes", F.when(F.col("image_id") % 10 != 0, F.col("hashes")))


def overlap_unreadable_part(spark, sf_dir):
    v = _unreadable(spark, sf_dir)
    return collide.overlap_matrix(v, SPLITS, "oo").unionByName(collide.overlap_matrix(v, SPLITS, "aa"))


def dedup_unreadable_part(spark, sf_dir):
    """Images that stay under each policy, the copies and the groups counted beside them."""
    v = _unreadable(spark, sf_dir).withColumn("split", F.lit("all"))
    out = None
    for policy in ("first_seen", "canonical"):
        kept = dedup.retain_unique(v, policy).agg(F.lit(policy).alias("what"), F.count(F.lit(1)).alias("n"))
        out = kept if out is None else out.unionByName(kept)
    h = v.select("image_id", "split", F.element_at("hashes", 1).alias("hash"))
    copies = collide.self_overlap(h).select(F.lit("copies").alias("what"), F.col("n_hits").alias("n"))
    groups = dedup.group_size_histogram(h).agg(F.lit("grouped").alias("what"), F.sum("n_images").alias("n"))
    return out.unionByName(copies).unionByName(groups)


def index_size_part(spark, sf_dir):
    return measures.index_size(versions(spark, sf_dir, "part"))


# ---- measures -------------------------------------------------------------------------


def _compare(name):
    def run(spark, sf_dir):
        return measures.compare_hashes(two_hashes(spark, sf_dir, name))

    return run, O.with_(f"{O.hashed(name)}, {O.ahash_cte()}", f"""
SELECT p.search, p.target, p.n_search, p.n_hits AS phash_hits, a.n_hits AS ahash_hits,
    p.overlap_pct AS phash_pct, a.overlap_pct AS ahash_pct
FROM ({O.matrix('v', 'v', 'oo', False)}) AS p JOIN ({O.matrix('ah', 'ah', 'oo', False)}) AS a USING (search, target)""")


def hash_agreement_part(spark, sf_dir):
    return measures.hash_agreement(two_hashes(spark, sf_dir, "part"))


def _precision(name):
    def run(spark, sf_dir):
        images = collection(spark, sf_dir, name).images
        return measures.collision_precision(hashes(spark, sf_dir, name), fp.content_digest(images))

    body = {"documents": ("doc_id", "text", "documents"), "part": ("p_partkey", "p_name || '|' || p_type", "part")}
    key, text, source = body[name]
    return run, O.with_(f"""{O.hashed(name)}, d AS (SELECT hash, {text} AS body FROM v JOIN {source} ON image_id = {key}),
c AS (SELECT hash, count(*) OVER (PARTITION BY hash) AS members, count(*) OVER (PARTITION BY hash, body) AS same FROM d)""",
        """SELECT count(*) FILTER (members > 1) AS n_flagged, count(*) FILTER (members > 1 AND same = 1) AS n_false,
    count(*) FILTER (members > 1 AND same > 1) AS n_exact,
    count(*) FILTER (members > 1 AND same > 1) / count(*) FILTER (members > 1)::DOUBLE AS precision FROM c""")


def verify_collisions_part(spark, sf_dir):
    h = hashes(spark, sf_dir, "part")
    index = reliable(collide.hash_index(h).where("n > 1"))
    pairs = join_by_key(h, index, ["hash"]).where("image_id > min_id").select(F.col("min_id").alias("id_a"), F.col("image_id").alias("id_b"))
    c = collection(spark, sf_dir, "part")
    return measures.verify_payloads(pairs, c.images, c.kind)


def planted_recall_by_op(spark, sf_dir):
    images = reliable(pixel_collection(spark, sf_dir, "embeddings"))
    copies = reliable(measures.planted_copies(images, ALL_OPS))
    spec = fp.Hash("hashes", threshold="mean_ac", ops=PAPER_OPS)
    made = fp.fingerprints(copies, "pixels", spec)
    tagged = made.join(copies.select("image_id", "source_id", "op"), "image_id")
    return measures.planted_recall(tagged, fp.fingerprints(images, "pixels", spec))


def depth_ablation_documents(spark, sf_dir):
    c = collection(spark, sf_dir, "documents")
    specs = [fp.Hash(f"d{k}", threshold="mean_ac", side=k) for k in (8, 12, 16)]
    deep = fp.fingerprints(c.images, c.kind, *specs)
    return measures.depth_ablation(deep, {"64": "d8", "144": "d12", "256": "d16"})


def _flat(name):
    def run(spark, sf_dir):
        pixels = reliable(pixel_collection(spark, sf_dir, name))
        return measures.flat_audit(fp.phash(pixels, threshold="mean_ac"), pixels.withColumnRenamed("payload", "pixels"))

    return run, O.with_(f"""{O.hashed(name)}, m AS (SELECT image_id, count(*) OVER (PARTITION BY hash) > 1 AS collided FROM v),
s AS (SELECT image_id, list_max(g) - list_min(g) AS contrast, len(list_filter(g, lambda x: x = 0)) AS zeros FROM ras)""",
        """SELECT collided, count(*) AS n, sum(contrast)::BIGINT AS sum_contrast, min(contrast)::INTEGER AS min_contrast,
    sum(zeros)::BIGINT AS sum_zero_cells FROM m JOIN s USING (image_id) GROUP BY collided""")


def _labels(spark, sf_dir):
    return table(spark, sf_dir, "labels").select(F.col("doc_id").alias("image_id"), F.col("quality").alias("label"))


def label_agreement_documents(spark, sf_dir):
    return measures.label_agreement(hashes(spark, sf_dir, "documents"), _labels(spark, sf_dir))


def memorization_gap_documents(spark, sf_dir):
    return measures.memorization_gap(hashes(spark, sf_dir, "documents"), _labels(spark, sf_dir))


def hash_health_documents(spark, sf_dir):
    return measures.hash_health(hashes(spark, sf_dir, "documents", "mean_all"))


def ops_ablation(spark, sf_dir):
    v = versions(spark, sf_dir, "part")
    return collide.ops_hits(_part(v, "train"), _part(v, "val"))


def gallery_val_in_train_documents(spark, sf_dir):
    h = hashes(spark, sf_dir, "documents")
    return galleries.gallery(_part(h, "val"), _part(h, "train"))


def gallery_two_hashes_part(spark, sf_dir):
    return galleries.gallery_two_hashes(two_hashes(spark, sf_dir, "part"), "val", "train")


def _unreadable_matrix() -> str:
    """Nine cells official and nine augmented, every tenth image in the sizes alone."""
    rows = []
    for mode, nth in (("oo", "nth = 0"), ("aa", "true")):
        for s in SPLITS:
            for t in SPLITS:
                size = f"(SELECT count(*) FROM r WHERE split = '{s}' AND {nth}) + (SELECT count(*) FROM ras WHERE split = '{s}' AND image_id % 10 = 0)"
                hits = f"(SELECT count(*) FROM r WHERE split = '{s}' AND {nth} AND hash IN (SELECT hash FROM r WHERE split = '{t}' AND {nth}))"
                if s == t and mode == "oo":
                    hits = f"(SELECT count(*) - count(DISTINCT hash) FROM r WHERE split = '{s}' AND nth = 0)"
                elif s == t:
                    size = f"(SELECT count(*) FROM ras WHERE split = '{s}')"
                    hits = f"(SELECT count(DISTINCT image_id) FROM r WHERE split = '{s}') - (SELECT count(*) FROM kept WHERE split = '{s}')"
                rows.append(f"SELECT '{s}' AS search, '{t}' AS target, '{mode}' AS mode, {size} AS n_search, {hits} AS n_hits")
    return O.with_(f"{O.hashed('part', ops=PAPER_OPS)}, r AS MATERIALIZED (SELECT * FROM v WHERE image_id % 10 <> 0), {O.kept_cte('r')}",
        f"SELECT *, 100.0::DOUBLE * n_hits / n_search AS overlap_pct FROM ({' UNION ALL '.join(rows)})")


def entries():
    doc, part = O.hashed("documents"), O.hashed("part")
    part6, doc6 = O.hashed("part", ops=PAPER_OPS), O.hashed("documents", ops=PAPER_OPS)
    kept = O.kept_cte()
    one = "(SELECT * EXCLUDE split, 'all' AS split FROM v)"
    pick = "SELECT image_id, split FROM kept"
    plain = "SELECT min(image_id) AS image_id, split FROM v GROUP BY hash, split"
    agree = " UNION ALL ".join(
        f"""SELECT '{s}' AS search, '{t}' AS target, count(*) FILTER (p AND a) AS n_both,
    count(*) FILTER (p AND NOT a) AS n_phash_only, count(*) FILTER (a AND NOT p) AS n_ahash_only
FROM (SELECT v.hash IN (SELECT hash FROM v WHERE split = '{t}') AS p, ah.hash IN (SELECT hash FROM ah WHERE split = '{t}') AS a
      FROM v JOIN ah USING (image_id) WHERE v.split = '{s}')"""
        for s in SPLITS
        for t in SPLITS
        if s != t
    )
    depth = " UNION ALL ".join(
        f"SELECT '{k * k}' AS depth, count(*) AS n, count(*) - count(DISTINCT b) AS n_redundant FROM (SELECT ["
        + ", ".join(O.hash_of("b", "mean_ac", i, min(i + 64, k * k)) for i in range(0, k * k, 64))
        + f"] AS b FROM blk{k})"
        for k in (8, 12, 16)
    )
    gallery = """f AS (SELECT hash, image_id AS match_id, row_number() OVER (PARTITION BY hash ORDER BY image_id) AS nth FROM {h} WHERE split = 'train'),
q AS (SELECT image_id AS query_id, hash FROM {h} WHERE split = 'val' AND hash IN (SELECT hash FROM f) ORDER BY 1 LIMIT 5)"""
    patches = """patches AS (SELECT id, substr(t, k * 200 + 1, 200) AS patch, kind FROM (
    SELECT doc_id AS id, text AS t, 'd' AS kind, unnest(range((length(text) - 1) // 200 + 1)) AS k FROM documents WHERE length(text) > 0
    UNION ALL SELECT item_id, text, 'i', unnest(range((length(text) - 1) // 200 + 1)) FROM benchmark WHERE length(text) > 0))"""
    return {
        "hash_index_documents": (hash_index_documents, O.with_(doc, "SELECT hash, min(image_id) AS min_id, count(*) AS n FROM v GROUP BY hash")),
        **{f"overlap_official_{n}": _official(n) for n in ("documents", "part", "pages", "embeddings", "conversations")},
        **{f"overlap_augmented_{n}": _augmented(n) for n in ("documents", "part", "pages", "embeddings")},
        "overlap_train_in_augmented_val": _one_way("train", "val", "oa"),
        "overlap_augmented_val_in_train": _one_way("val", "train", "ao"),
        "overlap_matrix_part_full": (
            overlap_matrix_part_full,
            O.with_(f"{part6}, official AS (SELECT * FROM v WHERE nth = 0), {kept}",
                    f"{O.matrix('official', 'official', 'oo', False)} UNION ALL {O.matrix('v', 'v', 'aa', True)}"),
        ),
        "self_redundancy_part": _self("redundant"),
        "self_members_part": _self("members"),
        "self_redundancy_augmented_part": (
            _self_augmented("first_seen"),
            O.with_(f"{part6}, w AS {one}, {O.kept_cte('w')}",
                    "SELECT count(DISTINCT image_id) AS n_search, count(DISTINCT image_id) - (SELECT count(*) FROM kept) AS n_hits FROM v"),
        ),
        "lookup_one": (lookup_one, O.with_(doc, """SELECT a.hash, min(b.image_id) AS min_id, nullif(count(b.hash), 0) AS n, count(b.hash) > 0 AS found
FROM (SELECT hash FROM v WHERE image_id = 1) AS a LEFT JOIN (SELECT * FROM v WHERE image_id <> 1) AS b ON a.hash = b.hash GROUP BY a.hash""")),
        "overlap_pages_documents": (
            overlap_pages_documents,
            O.with_(f"""{O.hashed('pages')}, dras AS MATERIALIZED (SELECT image_id, 'x' AS split, g FROM ({O.RASTERS['documents']})),
{O.block_ctes('dras', 'dblk')}, {O.version_ctes('mean_ac', block='dblk', out='dv')}""",
                """SELECT count(*) AS n_search, count(*) FILTER (hash IN (SELECT hash FROM dv)) AS n_hits,
    100.0::DOUBLE * count(*) FILTER (hash IN (SELECT hash FROM dv)) / count(*) AS overlap_pct FROM v"""),
        ),
        "benchmark_in_documents": (
            benchmark_in_documents,
            O.with_(f"""{O.hashed('benchmark')}, dras AS MATERIALIZED (SELECT image_id, 'x' AS split, g FROM ({O.RASTERS['documents']})),
{O.block_ctes('dras', 'dblk')}, {O.version_ctes('mean_ac', block='dblk', out='dv')}""",
                "SELECT count(*) AS n_items, count(*) FILTER (hash IN (SELECT hash FROM dv)) AS n_hash_hits FROM v"),
        ),
        "benchmark_patch_recall": (
            benchmark_patch_recall,
            O.with_(f"""{patches}, numbered AS MATERIALIZED (SELECT row_number() OVER () AS image_id, * FROM patches),
ras AS MATERIALIZED (SELECT image_id, 'x' AS split, g FROM ({O._scan('numbered', 'image_id', 'patch')})),
{O.block_ctes()}, {O.version_ctes('mean_ac')}, h AS (SELECT n.id, n.kind, v.hash FROM v JOIN numbered AS n USING (image_id)),
hit AS (SELECT * FROM h WHERE kind = 'i' AND hash IN (SELECT hash FROM h WHERE kind = 'd'))""",
                """SELECT count(DISTINCT id) AS n_items, count(*) AS n_patches, (SELECT count(DISTINCT id) FROM hit) AS n_items_hit,
    (SELECT count(*) FROM hit) AS n_patches_hit FROM h WHERE kind = 'i'"""),
        ),
        "near_matches_tau2_part": (near_matches_tau2_part, O.with_(f"{part}, u AS (SELECT DISTINCT hash FROM v)",
            "SELECT a.hash AS hash_a, b.hash AS hash_b, bit_count(xor(a.hash, b.hash))::INTEGER AS distance FROM u AS a JOIN u AS b ON a.hash < b.hash AND bit_count(xor(a.hash, b.hash)) <= 2")),
        "near_matches_tau4_embeddings": (near_matches_tau4_embeddings, O.with_(O.hashed("embeddings", "sign_ac"),
            """SELECT a.hash AS hash_a, b.hash AS hash_b, bit_count(xor(a.hash, b.hash))::INTEGER AS distance, a.i AS min_a, a.n AS n_a, b.i AS min_b, b.n AS n_b
FROM (SELECT hash, min(image_id) AS i, count(*) AS n FROM v GROUP BY hash) AS a JOIN (SELECT hash, min(image_id) AS i, count(*) AS n FROM v GROUP BY hash) AS b
ON a.hash < b.hash AND bit_count(xor(a.hash, b.hash)) <= 4""")),
        "hamming_pairs_brute_embeddings": (hamming_pairs_brute_embeddings, O.with_(O.hashed("embeddings", "sign_ac"),
            "SELECT a.image_id AS id_a, b.image_id AS id_b, bit_count(xor(a.hash, b.hash))::INTEGER AS distance FROM v AS a JOIN v AS b ON a.image_id < b.image_id AND bit_count(xor(a.hash, b.hash)) <= 16")),
        "lineitem_part_leakage": (lineitem_part_leakage, O.with_(f"""{part}, r AS (SELECT v.hash, o_orderdate >= TIMESTAMP '1997-01-01' AS late
    FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN v ON v.image_id = l_partkey)""",
            "SELECT count(*) FILTER (late) AS n_search, count(*) FILTER (late AND hash IN (SELECT hash FROM r WHERE NOT late)) AS n_hits FROM r")),
        "tile_patch_overlap_ledger": (tile_patch_overlap_ledger, O.with_(f"""tiles AS MATERIALIZED (SELECT image_id AS tile, g FROM ({O.RASTERS['ledger']})),
ras AS MATERIALIZED (SELECT tile * 4 + r * 2 + c AS image_id, {O.split_case('tile')} AS split, list_transform(range(1024), lambda i:
    g[(r * 16 + i // 64) * 32 + c * 16 + (i % 32) // 2 + 1]) AS g FROM tiles, range(2) AS a(r), range(2) AS b(c)),
{O.block_ctes()}, {O.version_ctes('mean_ac')}""", O.matrix("v", "v", "oo", False))),
        "dedup_official_documents": (_dedup("documents", ("id",), "first_seen"), O.with_(doc, plain)),
        "dedup_official_part": (_dedup("part", ("id",), "first_seen"), O.with_(part, plain)),
        "dedup_augmented_documents": (_dedup("documents", PAPER_OPS, "first_seen"), O.with_(f"{doc6}, {kept}", pick)),
        "dedup_augmented_part": (_dedup("part", PAPER_OPS, "first_seen"), O.with_(f"{part6}, {kept}", pick)),
        "dedup_components_part": (_dedup("part", PAPER_OPS, "components"), O.with_(
            f"""RECURSIVE {part6}, own AS (SELECT split, hash, min(image_id) AS owner FROM v GROUP BY ALL),
e AS MATERIALIZED (SELECT DISTINCT image_id AS a, owner AS b FROM v JOIN own USING (split, hash) WHERE image_id <> owner),
links AS MATERIALIZED (SELECT a, b FROM e UNION SELECT b, a FROM e),
reach AS (SELECT a, b FROM links UNION SELECT reach.a, links.b FROM reach JOIN links ON reach.b = links.a)""",
            f"SELECT image_id, split FROM ras WHERE image_id NOT IN (SELECT a FROM reach WHERE b < a)")),
        "dedup_canonical_part": (_dedup("part", ALL_OPS, "canonical"), O.with_(O.hashed("part", ops=ALL_OPS),
            "SELECT min(image_id) AS image_id, split FROM (SELECT image_id, split, min(hash) AS k FROM v GROUP BY ALL) GROUP BY split, k")),
        "duplicate_groups_documents": (duplicate_groups_documents, O.with_(doc,
            "SELECT * FROM (SELECT min(image_id) OVER (PARTITION BY hash) AS group_id, count(*) OVER (PARTITION BY hash) AS n, image_id FROM v) WHERE n > 1")),
        "group_size_histogram_part": (group_size_histogram_part, O.with_(part,
            "SELECT size, count(*) AS n_groups, sum(size)::BIGINT AS n_images FROM (SELECT count(*) AS size FROM v GROUP BY hash) GROUP BY size")),
        "remove_leakage_documents": (_remove("documents"), O.with_(f"{doc6}, {kept}, {_FINAL}",
            "SELECT image_id FROM kept WHERE split = 'train' AND image_id NOT IN (SELECT image_id FROM leak)")),
        "remove_leakage_part": (_remove("part"), O.with_(f"{part6}, {kept}, {_FINAL}",
            "SELECT image_id FROM kept WHERE split = 'train' AND image_id NOT IN (SELECT image_id FROM leak)")),
        "sanitize_report_documents": _sanitize("documents"),
        "sanitize_report_part": _sanitize("part"),
        "sanitize_three_way_part": (sanitize_three_way_part, O.with_(f"""{part6}, {kept}, k AS MATERIALIZED (SELECT v.* FROM v JOIN kept USING (image_id, split)),
val_out AS (SELECT DISTINCT image_id FROM k WHERE split = 'val' AND hash IN (SELECT hash FROM k WHERE split = 'test')),
train_out AS (SELECT DISTINCT image_id FROM k WHERE split = 'train' AND (hash IN (SELECT hash FROM k WHERE split = 'test')
    OR hash IN (SELECT hash FROM k WHERE split = 'val' AND image_id NOT IN (SELECT image_id FROM val_out))))""",
            """SELECT s AS split, (SELECT count(DISTINCT image_id) FROM v WHERE split = s) AS n_official,
    (SELECT count(*) FROM kept WHERE split = s) AS n_unique, (SELECT count(*) FROM kept WHERE split = s)
    - CASE s WHEN 'val' THEN (SELECT count(*) FROM val_out) WHEN 'train' THEN (SELECT count(*) FROM train_out) ELSE 0 END AS n_final
FROM (VALUES ('test'), ('val'), ('train')) AS t(s)""")),
        "leak_pairs_documents": (leak_pairs_documents, O.with_(f"""{doc}, f AS (SELECT hash, min(image_id) AS train_id, count(*) AS n_train
    FROM v WHERE split = 'train' GROUP BY hash)""",
            "SELECT image_id AS held_id, hash, train_id, n_train FROM v JOIN f USING (hash) WHERE split = 'val'")),
        "leak_members_documents": (leak_members_documents, O.with_(doc,
            "SELECT hash, image_id AS train_id FROM v WHERE split = 'train' AND hash IN (SELECT hash FROM v WHERE split = 'val')")),
        "write_clean_part": (write_clean_part, O.with_(f"{part6}, {kept}, {_FINAL}",
            """SELECT split, count(*) AS n, 6 * count(*) AS n_versions FROM kept
WHERE split = 'val' OR (split = 'train' AND image_id NOT IN (SELECT image_id FROM leak)) GROUP BY split""")),
        "overlap_unreadable_part": (overlap_unreadable_part, _unreadable_matrix()),
        "dedup_unreadable_part": (dedup_unreadable_part, O.with_(f"""{O.hashed('part', ops=ALL_OPS)}, r AS (SELECT * FROM v WHERE image_id % 10 <> 0),
gone AS (SELECT count(*) AS n FROM ras WHERE image_id % 10 = 0), own AS (SELECT hash, min(image_id) AS owner FROM r WHERE nth < 6 GROUP BY hash),
first AS (SELECT image_id FROM r JOIN own USING (hash) WHERE nth < 6 GROUP BY image_id HAVING min(owner) = image_id),
least AS (SELECT image_id, min(hash) AS k FROM r WHERE nth < 6 GROUP BY image_id)""",
            """SELECT 'first_seen' AS what, (SELECT count(*) FROM first) + n AS n FROM gone
UNION ALL SELECT 'canonical', (SELECT count(DISTINCT k) FROM least) + n FROM gone
UNION ALL SELECT 'copies', (SELECT count(*) - count(DISTINCT hash) FROM r WHERE nth = 0)
UNION ALL SELECT 'grouped', (SELECT count(*) FROM r WHERE nth = 0)""")),
        "index_size_part": (index_size_part, O.with_(part6, """SELECT count(DISTINCT image_id) AS n_images, count(*) AS n_versions,
    count(DISTINCT hash) AS n_keys, 8.0::DOUBLE * count(*) / count(DISTINCT image_id) AS bytes_an_image, 24 AS bytes_a_key FROM v""")),
        "compare_hashes_documents": _compare("documents"),
        "compare_hashes_part": _compare("part"),
        "hash_agreement_part": (hash_agreement_part, O.with_(f"{part}, {O.ahash_cte()}", agree)),
        "collision_precision_documents": _precision("documents"),
        "collision_precision_part": _precision("part"),
        "verify_collisions_part": (verify_collisions_part, O.with_(f"{part}, o AS (SELECT hash, min(image_id) AS id_a FROM v GROUP BY hash)",
            """SELECT id_a, id_b, d AS sum_abs_diff, d / 1024.0::DOUBLE AS mean_abs_diff FROM (SELECT o.id_a, v.image_id AS id_b,
    list_sum(list_transform(range(1, 1025), lambda i: abs(x.g[i] - y.g[i])))::BIGINT AS d
    FROM v JOIN o USING (hash) JOIN ras AS x ON x.image_id = o.id_a JOIN ras AS y ON y.image_id = v.image_id WHERE v.image_id > o.id_a)""")),
        "planted_recall_by_op": (planted_recall_by_op, "SELECT op, n, CASE WHEN op = 'id' THEN n ELSE 0 END AS found_oo, "
            "CASE WHEN op IN ('transpose', 'anti') THEN 0 ELSE n END AS found_oa, n AS found_aa FROM "
            "(SELECT op, count(*) AS n FROM embeddings, (VALUES " + ", ".join(f"('{op}')" for op in ALL_OPS) + ") AS t(op) GROUP BY op)"),
        "depth_ablation_documents": (depth_ablation_documents, O.with_(
            ", ".join([O.raster_cte("documents"), *[O.block_ctes(out=f"blk{k}", side=k) for k in (8, 12, 16)]]), depth)),
        "flat_audit_ledger": _flat("ledger"),
        "flat_audit_bigram": _flat("bigram"),
        "flat_audit_activity": _flat("activity"),
        "label_agreement_documents": (label_agreement_documents, O.with_(doc, """SELECT count(*) AS n_groups, coalesce(sum(n), 0)::BIGINT AS n_members,
    count(*) FILTER (low = high) AS n_agreeing FROM (SELECT count(*) AS n, min(quality) AS low, max(quality) AS high
    FROM v JOIN labels ON doc_id = image_id GROUP BY hash HAVING count(*) > 1)""")),
        "memorization_gap_documents": (memorization_gap_documents, O.with_(f"""{doc}, j AS (SELECT v.*, quality AS label FROM v JOIN labels ON doc_id = image_id),
tw AS (SELECT hash, arg_min(label, image_id) AS twin FROM j WHERE split = 'train' GROUP BY hash),
cm AS (SELECT (2 * sum(label) >= count(*))::INTEGER AS common FROM j WHERE split = 'train')""",
            """SELECT twin IS NOT NULL AS leaked, count(*) AS n, count(*) FILTER (coalesce(twin, common) = label) AS n_right,
    count(*) FILTER (coalesce(twin, common) = label) / count(*)::DOUBLE AS accuracy
FROM j LEFT JOIN tw USING (hash), cm WHERE split <> 'train' GROUP BY 1""")),
        "hash_health_documents": (hash_health_documents, O.with_(O.hashed("documents", "mean_all"),
            "SELECT b::INTEGER AS bit, count(*) AS n, sum(CASE WHEN b = 63 THEN (hash < 0)::INT ELSE (hash >> b::INT) & 1 END)::BIGINT AS n_set FROM v, range(64) AS r(b) GROUP BY b")),
        "ops_ablation": (ops_ablation, O.with_(part6, """SELECT t.op, (SELECT count(*) FROM v WHERE split = 'train' AND nth = 0) AS n_search,
    (SELECT count(*) FROM v AS s WHERE s.split = 'train' AND s.nth = 0 AND s.hash IN (SELECT hash FROM v AS w WHERE w.split = 'val' AND w.op = t.op)) AS n_hits
FROM (SELECT DISTINCT op FROM v) AS t""")),
        "gallery_val_in_train_documents": (gallery_val_in_train_documents, O.with_(f"{doc}, {gallery.format(h='v')}",
            "SELECT query_id, hash, nth, match_id FROM q JOIN f USING (hash) WHERE nth <= 3")),
        "gallery_two_hashes_part": (gallery_two_hashes_part, O.with_(f"""{part}, {O.ahash_cte()}, {gallery.format(h='v')},
f2 AS (SELECT hash, image_id AS match_id, row_number() OVER (PARTITION BY hash ORDER BY image_id) AS nth FROM ah WHERE split = 'train')""",
            """SELECT 'phash' AS method, query_id, nth, match_id FROM q JOIN f USING (hash) WHERE nth <= 3
UNION ALL SELECT 'ahash', ah.image_id, nth, match_id FROM ah JOIN f2 USING (hash) WHERE ah.image_id IN (SELECT query_id FROM q) AND nth <= 3""")),
    }
