"""Small samples of matches for looking at: a few queries, a few matches each."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def gallery(search: DataFrame, target: DataFrame, queries: int = 5, k: int = 3) -> DataFrame:
    """(query_id, hash, nth, match_id): the first queries with a match, k matches each.

    Both are (image_id, hash). The target is cut to k rows a hash before the join.
    """
    nth = F.row_number().over(Window.partitionBy("hash").orderBy("image_id"))
    few = target.select("hash", F.col("image_id").alias("match_id"), nth.alias("nth")).where(F.col("nth") <= k)
    wanted = (
        search.select(F.col("image_id").alias("query_id"), "hash")
        .join(target.select("hash").distinct(), "hash", "left_semi")
        .orderBy("query_id")
        .limit(queries)
    )
    return wanted.join(few, "hash").select("query_id", "hash", "nth", "match_id")


def gallery_two_hashes(both: DataFrame, search: str, target: str, queries: int = 5, k: int = 3) -> DataFrame:
    """gallery() under two hashes for the same queries: (method, query_id, nth, match_id).

    both is (image_id, split, phash, ahash); queries are those that the first finds.
    """
    own, other = both.where(F.col("split") == search), both.where(F.col("split") == target)
    first = gallery(own.select("image_id", F.col("phash").alias("hash")),
                    other.select("image_id", F.col("phash").alias("hash")), queries, k)
    chosen = first.select("query_id").distinct()
    rest = own.join(F.broadcast(chosen), own["image_id"] == chosen["query_id"], "left_semi")  # at most `queries`
    second = gallery(rest.select("image_id", F.col("ahash").alias("hash")),
                     other.select("image_id", F.col("ahash").alias("hash")), queries, k)
    return first.select(F.lit("phash").alias("method"), "query_id", "nth", "match_id").unionByName(
        second.select(F.lit("ahash").alias("method"), "query_id", "nth", "match_id")
    )
