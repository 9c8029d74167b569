"""Collision search: which images of one set have their fingerprint in another.

A fingerprint that very many rasters share (a blank tile) is one key of every shuffle
here. Counts go through partial aggregates, targets are made distinct before a join, and
nothing enumerates pairs of a group.

An image without a fingerprint (unreadable, too small) counts in the size of its set, as one
version, and in nothing else: it is in no index, hits nothing and is nobody's copy.
"""

from __future__ import annotations

from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitguard.functions.runtime import reliable
from splitguard.operators.orient import PAPER_OPS, explode_versions

SIDES = ("oo", "ao", "oa", "aa")


def overlap_pct(hits: Column, size: Column, digits: int | None = None, how: str = "round") -> Column:
    """100 * hits / size, null for an empty set; rounded or truncated to digits if given."""
    share = F.when(size > 0, F.lit(100.0) * hits / size)
    if digits is None:
        return share
    if how == "trunc":
        return F.when(size > 0, F.floor(F.lit(100 * 10**digits) * hits / size) / 10**digits)
    return F.round(share, digits)


def hash_index(hashed: DataFrame) -> DataFrame:
    """(hash, min_id, n): one combined shuffle on the hash."""
    return hashed.where("hash is not null").groupBy("hash").agg(
        F.min("image_id").alias("min_id"), F.count(F.lit(1)).alias("n")
    )


def _side(hashed: DataFrame, augmented: bool) -> DataFrame:
    """(image_id, split, hash) rows of (image_id, split, hashes): one, or one an operation."""
    if augmented:
        return hashed.select("image_id", "split", F.explode_outer("hashes").alias("hash"))
    return hashed.select("image_id", "split", F.element_at("hashes", 1).alias("hash"))


def overlap(search: DataFrame, target: DataFrame, sides: str = "oo") -> DataFrame:
    """One row (n_search, n_hits, overlap_pct) of a search set against a target set.

    Both are (image_id, split, hashes) with the identity first. sides says which is
    augmented: search first, target second. Hits are counted per row of the search side.
    """
    if sides not in SIDES:
        raise ValueError(f"sides must be one of {SIDES}")
    # Both sides are combined by hash before the join, so a hash is one row of either.
    wanted = _side(search, sides[0] == "a").groupBy("hash").agg(F.count(F.lit(1)).alias("n"))
    index = _side(target, sides[1] == "a").select("hash").distinct()
    joined = wanted.join(index.withColumn("known", F.lit(True)), "hash", "left")
    table = joined.agg(
        F.coalesce(F.sum("n"), F.lit(0)).alias("n_search"),
        F.coalesce(F.sum(F.when(F.col("known"), F.col("n"))), F.lit(0)).alias("n_hits"),
    )
    return table.withColumn("overlap_pct", overlap_pct(F.col("n_hits"), F.col("n_search")))


def any_leak(search: DataFrame, target: DataFrame, sides: str = "oa") -> bool:
    """Whether there is a single collision; stops at the first."""
    wanted = _side(search, sides[0] == "a").select("hash")
    index = _side(target, sides[1] == "a").select("hash").distinct()
    return bool(wanted.join(index, "hash", "left_semi").limit(1).count())


def self_overlap(hashed: DataFrame, count: str = "redundant") -> DataFrame:
    """One row (n_search, n_hits, overlap_pct) of (image_id, hash): copies to remove, or members
    of groups of two or more with count='members'."""
    index = hashed.groupBy("hash").agg(F.count(F.lit(1)).alias("n"))
    extra = F.col("n") - 1 if count == "redundant" else F.when(F.col("n") > 1, F.col("n")).otherwise(0)
    extra = F.when(F.col("hash").isNotNull(), extra)
    made = index.agg(
        F.coalesce(F.sum("n"), F.lit(0)).alias("n_search"),
        F.coalesce(F.sum(extra), F.lit(0)).cast("long").alias("n_hits"),
    )
    return made.withColumn("overlap_pct", overlap_pct(F.col("n_hits"), F.col("n_search")))


def overlap_matrix(
    hashed: DataFrame, splits: list[str], sides: str = "oo", mode: str | None = None
) -> DataFrame:
    """All ordered pairs of splits at once: (search, target, mode, n_search, n_hits, overlap_pct).

    One shuffle: versions are counted by hash and split, and a hash found in the target
    adds its count in the search split. A set against itself counts its removable
    copies; with augmented sides that is what first_seen de-duplication removes.
    """
    from splitguard.operators.dedup import retain_unique

    search = _side(hashed, sides[0] == "a")
    target = _side(hashed, sides[1] == "a")
    marks = [f"s{i}" for i in range(len(splits))], [f"t{i}" for i in range(len(splits))]
    sides_of = search.select("hash", "split", F.lit(True).alias("is_search"))
    if sides[0] == sides[1]:
        counted = search.select("hash", "split").groupBy("hash").agg(
            *[F.count_if(F.col("split") == s).alias(m) for s, m in zip(splits, marks[0])]
        )
        counted = counted.select("*", *[F.col(m).alias(t) for m, t in zip(*marks)])
    else:
        both = sides_of.union(target.select("hash", "split", F.lit(False).alias("is_search")))
        counted = both.groupBy("hash").agg(
            *[F.count_if(F.col("is_search") & (F.col("split") == s)).alias(m) for s, m in zip(splits, marks[0])],
            *[F.count_if(~F.col("is_search") & (F.col("split") == s)).alias(m) for s, m in zip(splits, marks[1])],
        )
    cells = []
    for (i, s), (j, t) in product(enumerate(splits), repeat=2):
        own, other = F.col(marks[0][i]), F.col(marks[1][j])
        hits = own - F.least(own, F.lit(1)) if i == j else F.when(other > 0, own).otherwise(0)
        hits = F.when(F.col("hash").isNotNull(), hits)
        cells.append(
            F.struct(
                F.lit(s).alias("search"),
                F.lit(t).alias("target"),
                F.coalesce(F.sum(own), F.lit(0)).alias("n_search"),
                F.coalesce(F.sum(hits), F.lit(0)).cast("long").alias("n_hits"),
            )
        )
    table = counted.agg(F.array(*cells).alias("cells")).select(F.inline("cells"))
    if "a" in sides:
        table = table.where("search != target")
        own = hashed.groupBy("split").agg(F.count(F.lit(1)).alias("n_search"))
        kept = retain_unique(hashed).groupBy("split").agg(F.count(F.lit(1)).alias("kept"))
        copies = own.join(F.broadcast(kept), "split").where(F.col("split").isin(splits))  # a row a split
        table = table.unionByName(
            copies.select(
                F.col("split").alias("search"),
                F.col("split").alias("target"),
                "n_search",
                (F.col("n_search") - F.col("kept")).alias("n_hits"),
            )
        )
    return table.select(
        "search",
        "target",
        F.lit(mode or sides).alias("mode"),
        "n_search",
        "n_hits",
        overlap_pct(F.col("n_hits"), F.col("n_search")).alias("overlap_pct"),
    )


def lookup(hashes: DataFrame, index: DataFrame) -> DataFrame:
    """(hash, min_id, n, found) of wanted hashes in an index."""
    return hashes.select("hash").distinct().join(index, "hash", "left").select(
        "hash", "min_id", "n", F.col("n").isNotNull().alias("found")
    )


#: Queries of a search that are broadcast at once.
BLOCK_QUERIES = 100_000


def hamming_search(queries: DataFrame, rows: DataFrame, tau: int) -> DataFrame:
    """(a, b, distance) of stated queries against all rows, by comparing hashes, at any distance.

    Queries are compared in blocks of a size known beforehand: rows are read once a block.
    For distances of few bits, near_hashes is the way.
    """
    queries = reliable(queries.select(F.col("image_id").alias("a"), F.col("hash").alias("ha")).where("ha is not null"))
    blocks = -(-queries.count() // (BLOCK_QUERIES // 2)) or 1
    block = F.pmod(F.xxhash64("a"), F.lit(blocks))  # half full on average
    rows = rows.select(F.col("image_id").alias("b"), F.col("hash").alias("hb"))
    far, out = F.bit_count(F.col("ha").bitwiseXOR(F.col("hb"))), None
    for k in range(blocks):
        near = rows.join(F.broadcast(queries.where(block == k)), far <= tau)
        near = near.select("a", "b", far.cast("int").alias("distance"))
        out = near if out is None else out.unionByName(near)
    return out


def brute_force_pairs(a: DataFrame, b: DataFrame, tau: int) -> DataFrame:
    """(id_a, id_b, distance) by comparing all pairs: the baseline that near_hashes is held against.

    Its work grows with the square of the rows; its memory doesn't, since a goes by in blocks.
    """
    near = hamming_search(a, b, tau).where("a < b")
    return near.select(F.col("a").alias("id_a"), F.col("b").alias("id_b"), "distance")


def ops_hits(search: DataFrame, target: DataFrame, ops: tuple[str, ...] = PAPER_OPS) -> DataFrame:
    """(op, n_search, n_hits): official search images found by each operation of the target."""
    wanted = _side(search, False).select("image_id", "hash")
    index = explode_versions(target, ops).select("op", "hash").distinct()
    total = wanted.agg(F.count(F.lit(1)).alias("n_search"))
    found = (
        index.join(wanted.groupBy("hash").agg(F.count(F.lit(1)).alias("n")), "hash")
        .groupBy("op")
        .agg(F.sum("n").alias("n_hits"))
    )
    every = found.sparkSession.createDataFrame([(op,) for op in ops], "op string")
    return (
        every.join(F.broadcast(found), "op", "left")  # a row an operation
        .join(F.broadcast(total), how="left")
        .select("op", "n_search", F.coalesce("n_hits", F.lit(0)).alias("n_hits"))
    )
