"""Connected components by alternating large-star and small-star contraction.

Each round is two equi joins whose inputs are both re-read from checkpoints, so
adaptive execution may split a hot centre, and partially aggregated minima.
The driver sees two numbers per round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitguard.functions.runtime import reliable


def _star(edges: DataFrame, both: bool) -> DataFrame:
    """One star step on edges (hi, lo), hi > lo.

    both=True is the large star: every greater neighbour moves to the least of
    the closed neighbourhood. both=False is the small star: the node and its
    lesser neighbours move to the least lesser neighbour.
    """
    if both:
        around = edges.union(edges.select(F.col("lo").alias("hi"), F.col("hi").alias("lo")))
        centre = around.groupBy(F.col("hi").alias("at")).agg(F.min("lo").alias("least"))
        centre = reliable(centre.select("at", F.least("at", "least").alias("least")))
        moved = (
            around.join(centre, around["hi"] == centre["at"])
            .where(F.col("lo") > F.col("hi"))
            .select(F.col("lo").alias("hi"), F.col("least").alias("lo"))
        )
    else:
        centre = reliable(edges.groupBy(F.col("hi").alias("at")).agg(F.min("lo").alias("least")))
        moved = (
            edges.join(centre, edges["hi"] == centre["at"])
            .where(F.col("lo") != F.col("least"))
            .select(F.col("lo").alias("hi"), F.col("least").alias("lo"))
            .union(centre.select(F.col("at").alias("hi"), F.col("least").alias("lo")))
        )
    return reliable(moved.where(F.col("hi") != F.col("lo")).distinct())


def _mark(edges: DataFrame) -> tuple[int, int]:
    row = edges.agg(
        F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("hi", "lo")).alias("x")
    ).first()
    return row["n"], row["x"]


def connected_components(edges: DataFrame, a: str, b: str, max_rounds: int = 64) -> DataFrame:
    """(node, component) for every node of an edge; component is the least node reachable.

    Self loops and nulls carry no link. An empty edge table gives an empty result.
    """
    kind = edges.schema[a].dataType
    left, right = F.col(a).cast(kind), F.col(b).cast(kind)
    edge = reliable(
        edges.where(left != right)
        .select(F.greatest(left, right).alias("hi"), F.least(left, right).alias("lo"))
        .distinct()
    )
    seen = _mark(edge)
    for _ in range(max_rounds):
        if not seen[0]:
            break
        edge = _star(_star(edge, True), False)
        now = _mark(edge)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    leaves = edge.select(F.col("hi").alias("node"), F.col("lo").alias("component"))
    roots = edge.select(F.col("lo").alias("node"), F.col("lo").alias("component")).distinct()
    return leaves.union(roots)
