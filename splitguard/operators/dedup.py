"""De-duplication within splits, leak removal between them, and the whole cleaning."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitguard.functions.runtime import join_by_key, reliable
from splitguard.operators.components import connected_components

POLICIES = ("first_seen", "components", "canonical")


def _versions(hashed: DataFrame) -> DataFrame:
    return hashed.select("image_id", "split", F.explode("hashes").alias("hash")).where("hash is not null")


def _with_owner(versions: DataFrame) -> DataFrame:
    """versions with the least image of their split that has the hash.

    Hashes held by one version own themselves and are left out of the join; hot ones are
    joined apart.
    """
    versions = reliable(versions)
    index = versions.groupBy("split", "hash").agg(
        F.min("image_id").alias("owner"), F.count(F.lit(1)).alias("n")
    )
    index = reliable(index.where("n > 1"))
    both = join_by_key(versions, index, ["split", "hash"], how="left")
    return both.withColumn("owner", F.coalesce("owner", "image_id"))


def retain_unique(hashed: DataFrame, policy: str = "first_seen") -> DataFrame:
    """Rows of (image_id, split, hashes) that stay; each split is cleaned on its own.

    first_seen: an image goes if a smaller id of its split shares any of its hashes.
    components: the least id of each transitive group stays.
    canonical: the least of all oriented hashes is one key; hashes should hold all eight.
    Images without a hash stay under every policy.
    """
    if policy == "canonical":
        key = F.array_min("hashes")
        keyed = hashed.select("split", "image_id", key.alias("key")).where("key is not null")
        first = keyed.groupBy("split", "key").agg(F.min("image_id").alias("image_id"))
        kept = hashed.join(first.select("split", "image_id"), ["split", "image_id"], "left_semi")
        return kept.unionByName(hashed.where(key.isNull()))
    owned = _with_owner(_versions(hashed))
    if policy == "first_seen":
        gone = owned.where(F.col("owner") < F.col("image_id")).select("split", "image_id").distinct()
        return hashed.join(gone, ["split", "image_id"], "left_anti")
    if policy != "components":
        raise ValueError(f"policy must be one of {POLICIES}")
    # A node is (split, image); an edge joins an image to the owner of one of its hashes.
    edges = owned.where(F.col("owner") < F.col("image_id")).select(
        F.struct("split", "image_id").alias("a"),
        F.struct("split", F.col("owner").alias("image_id")).alias("b"),
    )
    nodes = connected_components(edges, "a", "b")
    gone = nodes.where(F.col("node") != F.col("component")).select("node.split", "node.image_id")
    return hashed.join(gone, ["split", "image_id"], "left_anti")


def duplicate_groups(hashed: DataFrame) -> DataFrame:
    """(group_id, n, image_id): one row for every image of a group of two or more equal hashes."""
    hashed = hashed.select("hash", "image_id").where("hash is not null")
    index = hashed.groupBy("hash").agg(F.min("image_id").alias("group_id"), F.count(F.lit(1)).alias("n"))
    index = reliable(index.where("n > 1").withColumn("size", F.col("n")))
    found = join_by_key(hashed, index, ["hash"])
    return found.select("group_id", F.col("size").alias("n"), "image_id")


def group_size_histogram(hashed: DataFrame) -> DataFrame:
    """(size, n_groups, n_images)."""
    sizes = hashed.where("hash is not null").groupBy("hash").agg(F.count(F.lit(1)).alias("size"))
    return sizes.groupBy("size").agg(
        F.count(F.lit(1)).alias("n_groups"), F.sum("size").alias("n_images")
    )


def remove_leakage(train: DataFrame, held: DataFrame, sides: str = "aa") -> DataFrame:
    """Rows of train that share no hash with held."""
    wanted = (
        _versions(train) if sides[0] == "a" else train.select("image_id", "split", F.element_at("hashes", 1).alias("hash"))
    )
    held_hashes = F.explode("hashes") if sides[1] == "a" else F.element_at("hashes", 1)
    index = held.select(held_hashes.alias("hash")).distinct()
    leaking = wanted.join(index, "hash", "left_semi").select("image_id").distinct()
    return train.join(leaking, "image_id", "left_anti")


def sanitize(
    hashed: DataFrame,
    policy: str = "first_seen",
    priority: tuple[str, ...] = ("val", "train"),
    sides: str = "aa",
    order: str = "dedup_first",
) -> tuple[DataFrame, DataFrame]:
    """(clean rows, report): each split de-duplicated, and later splits pruned of earlier ones.

    priority lists the splits to clean, the one that keeps its images first. The report
    is (split, n_official, n_unique, n_final), one row a split.
    """
    parts = {s: hashed.where(F.col("split") == s) for s in priority}
    unique, final = {}, {}
    for i, s in enumerate(priority):
        own = parts[s]
        if order == "prune_first":
            for t in priority[:i]:
                own = remove_leakage(own, parts[t], sides)
        unique[s] = reliable(retain_unique(own, policy))
        final[s] = unique[s]
        if order == "dedup_first":
            for t in priority[:i]:
                final[s] = remove_leakage(final[s], final[t], sides)
            final[s] = reliable(final[s])
    report = None
    for s in priority:
        counts = [x.agg(F.count(F.lit(1)).alias("n")) for x in (parts[s], unique[s], final[s])]
        row = counts[0].select(F.lit(s).alias("split"), F.col("n").alias("n_official"))
        row = row.join(counts[1].select(F.col("n").alias("n_unique")), how="left")  # rows of one count
        row = row.join(counts[2].select(F.col("n").alias("n_final")), how="left")
        report = row if report is None else report.unionByName(row)
    clean = final[priority[0]]
    for s in priority[1:]:
        clean = clean.unionByName(final[s].select(*clean.columns))
    return clean, report


def leak_pairs(train: DataFrame, held: DataFrame) -> DataFrame:
    """(held_id, hash, train_id, n_train): every held image whose hash is in train, with the least
    train image of the hash and their number; leak_members lists the others."""
    index = train.where("hash is not null").groupBy("hash").agg(
        F.min("image_id").alias("train_id"), F.count(F.lit(1)).alias("n_train")
    )
    held = held.select(F.col("image_id").alias("held_id"), "hash")
    wanted = held.groupBy("hash").agg(F.count(F.lit(1)).alias("n"))
    return join_by_key(held, reliable(index.join(wanted, "hash")), ["hash"]).select(
        "held_id", "hash", "train_id", "n_train"
    )


def leak_members(train: DataFrame, held: DataFrame) -> DataFrame:
    """(hash, train_id): every train image whose hash is in held; with leak_pairs, all links."""
    return train.join(held.select("hash").distinct(), "hash", "left_semi").select(
        "hash", F.col("image_id").alias("train_id")
    )


def write_clean(clean: DataFrame, path: str) -> None:
    """Cleaned rows as Parquet, one folder a split."""
    clean.write.mode("overwrite").partitionBy("split").parquet(path)
