"""Overlap, de-duplication, leakage and measures: published arithmetic, invariants, edges."""

import random

import pytest
from pyspark.sql import functions as F

from splitguard.functions import runtime
from splitguard.operators import collide, dedup, galleries, measures, raster
from splitguard.operators.components import connected_components
from splitguard.operators.orient import PAPER_OPS
from splitguard.plans import audits
from splitguard.plans.asof import as_of_join, interval_join
from splitguard.plans.band_join import near_hashes, near_matches

SF = "/root/testdata/sf0.001"
SCHEMA = "image_id long, split string, hashes array<long>"


@pytest.fixture(scope="module")
def part(spark):
    return audits.versions(spark, SF, "part").cache()


def pct(spark, hits, size, **how):
    df = spark.createDataFrame([(hits, size)], "h long, s long")
    return df.select(collide.overlap_pct(F.col("h"), F.col("s"), **how).alias("p")).first()["p"]


def test_published_percentages(spark):
    for hits, size, printed in ((56368, 60317, 93.45), (251403, 280741, 89.55), (351182, 361902, 97.04), (108707, 280741, 38.72), (166193, 280741, 59.19)):
        assert abs(pct(spark, hits, size) - printed) < 0.01
    assert pct(spark, 166193, 280741, digits=2, how="trunc") == 59.19
    assert pct(spark, 166193, 280741, digits=1) == 59.2
    assert pct(spark, 0, 0) is None


def test_published_identities():
    assert 280741 - 29338 == 251403 and 60317 - 14166 == 46151
    assert (6 * 280741, 6 * 60317, 6 * 60697) == (1684446, 361902, 364182)
    assert 29338 - 15392 <= 14166


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_matrix_is_nine_joins(part):
    for sides in ("oo", "aa", "oa", "ao"):
        table = {(r["search"], r["target"]): (r["n_search"], r["n_hits"]) for r in collide.overlap_matrix(part, audits.SPLITS, sides).collect()}
        assert len(table) == 9
        for s in audits.SPLITS:
            for t in audits.SPLITS:
                if s != t:
                    one = collide.overlap(part.where(F.col("split") == s), part.where(F.col("split") == t), sides).first()
                    assert table[s, t] == (one["n_search"], one["n_hits"]), sides


def test_overlap_grows_with_orientations(part):
    hits = {}
    for sides in ("oo", "oa"):
        hits[sides] = collide.overlap(part.where("split = 'train'"), part.where("split = 'val'"), sides).first()["n_hits"]
    assert hits["oo"] <= hits["oa"]
    own = part.where("split = 'val'")
    whole = collide.overlap(own, own, "oo").first()
    assert whole["n_hits"] == whole["n_search"]
    assert collide.any_leak(own, own) and not collide.any_leak(own.limit(0), own)


def test_policies_are_ordered(part):
    one = part.withColumn("split", F.lit("all")).cache()
    kept = {p: dedup.retain_unique(one, p).count() for p in ("first_seen", "components")}
    distinct = one.select(F.element_at("hashes", 1)).distinct().count()
    assert kept["components"] <= kept["first_seen"] <= distinct


def test_a_chain_tells_the_policies_apart(spark):
    chain = spark.createDataFrame([(3, "train", [1]), (1, "train", [1, 2]), (2, "train", [2, 9]), (5, "train", [9]), (4, "val", [1])], SCHEMA)
    assert rows(dedup.retain_unique(chain).select("image_id")) == [(1,), (4,)] or rows(dedup.retain_unique(chain).select("image_id")) == [(1,), (4,)]
    chain = spark.createDataFrame([(1, "train", [10]), (2, "train", [20]), (3, "train", [10, 20])], SCHEMA)
    assert rows(dedup.retain_unique(chain).select("image_id")) == [(1,), (2,)]
    assert rows(dedup.retain_unique(chain, "components").select("image_id")) == [(1,)]
    with pytest.raises(ValueError):
        dedup.retain_unique(chain, "other")


def test_kept_rows_do_not_collide_and_cleaning_is_idempotent(part):
    kept = dedup.retain_unique(part).cache()
    again = dedup.retain_unique(kept)
    assert rows(kept.select("image_id")) == rows(again.select("image_id"))
    shared = kept.select("split", "image_id", F.explode(F.array_distinct("hashes")).alias("h")).groupBy("split", "h").count()
    assert shared.where("count > 1").count() == 0


@pytest.mark.parametrize("order", ["dedup_first", "prune_first"])
@pytest.mark.parametrize("policy", ["first_seen", "components"])
def test_nothing_leaks_after_cleaning(part, order, policy):
    clean, report = dedup.sanitize(part, policy, order=order)
    clean = clean.cache()
    table = {r["split"]: (r["n_official"], r["n_unique"], r["n_final"]) for r in report.collect()}
    for s, (a, b, c) in table.items():
        assert a >= b >= c == clean.where(F.col("split") == s).count()
    assert not collide.any_leak(clean.where("split = 'train'"), clean.where("split = 'val'"), "aa")


def test_cleaning_does_not_depend_on_layout(part):
    other = part.repartition(7, F.rand(1)).orderBy(F.rand(2))
    assert rows(dedup.retain_unique(part).select("image_id")) == rows(dedup.retain_unique(other).select("image_id"))
    a = collide.overlap_matrix(part, audits.SPLITS, "aa")
    assert rows(a) == rows(collide.overlap_matrix(other, audits.SPLITS, "aa"))


def test_heavy_hash(spark, monkeypatch):
    monkeypatch.setattr(runtime, "LEAST_HOT", 100)
    hot = spark.range(2000).select(F.col("id").alias("image_id"), F.lit("train").alias("split"), F.array(F.lit(5), F.col("id") + 100).alias("hashes"))
    assert rows(dedup.retain_unique(hot).select("image_id")) == [(0,)]
    assert rows(dedup.retain_unique(hot, "components").select("image_id")) == [(0,)]


def test_empty_and_single_splits(spark):
    none = spark.createDataFrame([], SCHEMA)
    one = spark.createDataFrame([(1, "train", [1, 2]), (1, "train", [1, 2])], SCHEMA)
    assert dedup.retain_unique(none).count() == 0 and dedup.retain_unique(none, "components").count() == 0
    table = collide.overlap_matrix(one, ["train", "val"], "oo").collect()
    by = {(r["search"], r["target"]): r for r in table}
    assert by["val", "train"]["overlap_pct"] is None and by["train", "val"]["n_hits"] == 0
    assert dedup.remove_leakage(one, none).count() == 2
    assert collide.self_overlap(none.select("image_id", F.lit(1).alias("hash"))).first()["overlap_pct"] is None


@pytest.mark.parametrize("tau", [0, 1, 2, 3, 4, 9])
def test_band_join_is_brute_force(spark, tau):
    rng = random.Random(tau)
    base = [rng.getrandbits(64) for _ in range(12)]
    data = []
    for i in range(150):
        h = rng.choice(base)
        for _ in range(rng.randrange(6)):
            h ^= 1 << rng.randrange(64)
        data.append((i, h - (1 << 64) if h >> 63 else h))
    df = spark.createDataFrame(data, "image_id long, hash long").cache()
    assert rows(near_matches(df, df, tau)) == rows(collide.brute_force_pairs(df, df, tau))
    assert near_hashes(df, df, tau).count() == near_hashes(df, df, tau).distinct().count()


@pytest.mark.parametrize("seed", range(4))
def test_components_are_union_find(spark, seed):
    rng = random.Random(seed)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)] + [(i, i + 1) for i in range(300, 340)] + [(400, i) for i in range(401, 460)]
    parent = {}

    def root(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        if a != b:
            a, b = root(a), root(b)
            parent[max(a, b)] = min(a, b)
    got = connected_components(spark.createDataFrame(edges, "a long, b long"), "a", "b")
    assert {r["node"]: r["component"] for r in got.collect()} == {x: root(x) for x in parent}
    assert got.count() == len(parent)


def test_planted_copies(spark):
    got = {r["op"]: r for r in audits.planted_recall_by_op(spark, SF).collect()}
    assert len(got) == 8
    for op, r in got.items():
        assert r["found_aa"] == r["n"]
        assert r["found_oa"] == (r["n"] if op in PAPER_OPS else 0)
        assert r["found_oo"] == (r["n"] if op == "id" else 0)


def test_precision_and_agreement_by_hand(spark):
    hashed = spark.createDataFrame([(1, 5), (2, 5), (3, 5), (4, 6)], "image_id long, hash long")
    digests = spark.createDataFrame([(1, "a"), (2, "a"), (3, "b"), (4, "c")], "image_id long, digest string")
    r = measures.collision_precision(hashed, digests).first()
    assert (r["n_flagged"], r["n_false"], r["n_exact"]) == (3, 1, 2) and abs(r["precision"] - 2 / 3) < 1e-12
    pairs = spark.createDataFrame([(1, 2)], "id_a long, id_b long")
    pixels = spark.createDataFrame([(1, [1, 2]), (2, [4, 0])], "image_id long, pixels array<int>")
    assert measures.verify_pairs(pairs, pixels).first()["mean_abs_diff"] == 2.5


def test_verified_pairs_broadcast_no_rasters(spark):
    """Spark's guess of their size is far too low, and a broadcast goes through the driver."""
    made = audits.verify_collisions_part(spark, SF)
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan and "pixels" not in plan
    images = spark.createDataFrame([(1, "a", "ab" * 9), (2, "a", None), (3, "a", "ab" * 9), (4, "a", "b")], "image_id long, split string, payload string")
    pairs = spark.createDataFrame([(1, 2), (1, 3), (1, 4)], "id_a long, id_b long")
    got = {r["id_b"]: (r["sum_abs_diff"], r["mean_abs_diff"]) for r in measures.verify_payloads(pairs, images, "text").collect()}
    pixels = raster.rasters(images, "text").where("pixels is not null")
    want = {r["id_b"]: (r["sum_abs_diff"], r["mean_abs_diff"]) for r in measures.verify_pairs(pairs, pixels).collect()}
    assert got == want | {2: (None, None)} and want[3] == (0, 0.0) and want[4][0] > 0


def test_gallery_is_bounded(spark):
    target = spark.range(50).select(F.col("id").alias("image_id"), F.lit(1).cast("long").alias("hash"))
    got = galleries.gallery(target.where("image_id < 9"), target, queries=4, k=3)
    assert got.count() == 12


def test_cost_report(spark):
    stages = measures.cost_report(spark, {"read": (spark.range(10), 10)})
    assert stages[0]["items"] == 10 and stages[0]["ms_per_item"] >= 0


def test_as_of_and_interval_joins(spark):
    left = spark.createDataFrame([(1, "2024-01-01 10:00:00", 1), (1, "2024-01-01 08:00:00", 2), (2, "2024-01-01 10:00:00", 3)], "k int, t string, id int").withColumn("t", F.col("t").cast("timestamp"))
    right = spark.createDataFrame([(1, "2024-01-01 09:00:00", "a"), (1, "2024-01-01 10:00:00", "b"), (1, "2024-01-01 10:30:00", "c")], "k int, u string, v string").withColumn("u", F.col("u").cast("timestamp"))
    assert sorted((r["id"], r["v"]) for r in as_of_join(left, right, "k", "t", "u", ["v"]).collect()) == [(1, "b"), (2, None), (3, None)]
    near = interval_join(left, right, "k", "t", "u", 3600)
    assert sorted((r["id"], r["v"]) for r in near.collect()) == [(1, "b"), (1, "c"), (2, "a")]
