"""Sources, sinks, streams and SQL functions."""

import json
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from splitguard import catalogue
from splitguard.operators import dedup
from splitguard.operators.fingerprint import hash_hex
from splitguard.plans import audits, tables
from splitguard.sources import files
from splitguard.streaming import guard

SF = "/root/testdata/sf0.001"
GREY = np.random.default_rng(1).integers(0, 256, (40, 33))


@pytest.fixture
def images(tmp_path):
    h, w = GREY.shape
    (tmp_path / "in").mkdir()
    (tmp_path / "in" / "a.pgm").write_bytes(b"P5\n# note\n%d %d\n255\n" % (w, h) + GREY.astype(np.uint8).tobytes())
    (tmp_path / "in" / "b.pgm").write_bytes(b"P2 %d %d 255\n" % (w, h) + " ".join(map(str, GREY.ravel())).encode())
    colour = np.stack([GREY] * 3, axis=-1)
    (tmp_path / "c.ppm").write_bytes(b"P6 %d %d 255\n" % (w, h) + colour.astype(np.uint8).tobytes())
    (tmp_path / "d.ppm").write_bytes(b"P6 9 9 255\nshort")
    (tmp_path / "e.txt").write_text("no image")
    return tmp_path


def test_raster_files(spark, images):
    got = {r["path"].rsplit("/", 1)[1]: r for r in files.read_rasters(spark, str(images)).collect()}
    assert sorted(got) == ["a.pgm", "b.pgm", "c.ppm", "d.ppm"]
    for name in ("a.pgm", "b.pgm", "c.ppm"):
        assert got[name]["pixels"] == GREY.ravel().tolist() and got[name]["reason"] is None
    assert got["d.ppm"]["pixels"] is None and got["d.ppm"]["reason"]


def test_raster_data_source(spark, images):
    spark.dataSource.register(files.RasterSource)
    paths = f"{images}/in/a.pgm,{images}/d.ppm"
    got = {r["path"]: r for r in spark.read.format("raster").option("paths", paths).load().collect()}
    assert got[f"{images}/in/a.pgm"]["height"] == 40 and got[f"{images}/d.ppm"]["reason"]


def test_annotations_and_hash_list(spark, tmp_path):
    data = {
        "images": [{"id": 1, "file_name": "a", "height": 3, "width": 3}, {"id": 2, "file_name": "b"}],
        "annotations": [{"id": 7, "image_id": 1, "category_id": 4, "segmentation": [[0.0, 1.0, 2.0, 3.0]]}],
    }
    (tmp_path / "x.json").write_text(json.dumps(data))
    got = sorted(tuple(r) for r in files.read_annotations(spark, str(tmp_path / "x.json")).collect())
    assert got[0] == (1, "a", 7, 4, 4) and got[1][:3] == (2, "b", None)
    (tmp_path / "h.csv").write_text("image_id,hash_hex\n1,00000000000000ff\n2,ffffffffffffffff\n")
    assert sorted(tuple(r) for r in files.read_hash_list(spark, str(tmp_path / "h.csv")).collect()) == [(1, 255), (2, -1)]


def test_sinks(spark, tmp_path):
    hashed = audits.versions(spark, SF, "part")
    files.write_index(hashed, str(tmp_path / "index"))
    back = spark.read.parquet(str(tmp_path / "index")).where("split = 'val'")
    assert "PartitionFilters: [isnotnull(split" in back._jdf.queryExecution().toString()
    assert back.count() == hashed.where("split = 'val'").count()
    clean, report = dedup.sanitize(hashed)
    dedup.write_clean(clean, str(tmp_path / "clean"))
    assert spark.read.parquet(str(tmp_path / "clean")).count() == clean.count()
    report.write.json(str(tmp_path / "report"))
    assert spark.read.json(str(tmp_path / "report")).count() == 2


def test_bucketed_index_needs_no_shuffle(spark):
    hashed = audits.versions(spark, SF, "part", ("id",))
    spark.sql("DROP TABLE IF EXISTS bucketed_index")
    files.write_bucketed_index(hashed, "bucketed_index", 4)
    plan = spark.table("bucketed_index").groupBy("hash").count()._jdf.queryExecution().toString()
    assert "Exchange" not in plan
    spark.sql("DROP TABLE bucketed_index")


def test_filters_reach_the_scan(spark):
    plan = tables.scan_pruned_documents(spark, SF)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(n_chars), IsNotNull(lang), GreaterThan(n_chars,2000), EqualTo(lang,en)]" in plan
    assert "ReadSchema: struct<doc_id:bigint,lang:string,n_chars:bigint>" in plan


def _events(spark, folder, rows):
    df = spark.createDataFrame(rows, "event_id long, ts string, k string").withColumn("ts", F.col("ts").cast("timestamp"))
    df.coalesce(1).write.mode("append").parquet(folder)
    return df.schema


def test_stream_goes_on_from_its_checkpoint_and_drops_late_rows(spark, tmp_path):
    source, out, mark = (str(tmp_path / x) for x in ("in", "out", "mark"))
    schema = _events(spark, source, [(1, "2024-01-01 00:00:00", "a"), (2, "2024-01-01 00:05:00", "a"), (3, "2024-01-03 00:00:00", "b")])

    def run():
        stream = spark.readStream.schema(schema).parquet(source)
        guard.run_to_parquet(guard.first_arrivals(stream, "k", "1 hour"), out, mark)
        return sorted(r["event_id"] for r in spark.read.parquet(out).collect())

    first = run()
    assert 3 in first and len(first) == 2
    assert run() == first
    _events(spark, source, [(4, "2024-01-03 00:10:00", "b"), (5, "2024-01-01 00:00:00", "late"), (6, "2024-01-03 00:20:00", "c")])
    assert run() == sorted([*first, 6])


def test_leak_guard_per_batch(spark, tmp_path):
    source = str(tmp_path / "in")
    arrivals = spark.createDataFrame([(1, 10), (2, 20)], "event_id long, hash long")
    arrivals.write.parquet(source)
    index = spark.createDataFrame([(20,)], "hash long")
    seen = []
    stream = spark.readStream.schema(arrivals.schema).parquet(source)
    guard.run_per_batch(guard.leak_guard(stream, index), lambda b, n: seen.extend((r["event_id"], r["leaks"]) for r in b.collect()), str(tmp_path / "mark"))
    assert sorted(seen) == [(1, False), (2, True)]


def test_streams_read_tables_in_many_files(spark, tmp_path):
    """A table is one file or a folder of files; a stream must read either whole."""
    for name in ("documents", "events"):
        spark.read.parquet(f"{SF}/{name}.parquet").repartition(3).write.parquet(f"{tmp_path}/{name}.parquet")
    for query in ("stream_leak_guard", "stream_tumbling_events"):
        one, many = (sorted(map(tuple, catalogue.queries()[query](spark, d).collect()), key=repr) for d in (SF, str(tmp_path)))
        assert one and many == one


def test_entry(spark):
    report = __spark_entry__.entry(spark)
    assert report.columns == ["split", "n_official", "n_unique", "n_final"] and report.count() == 2


def test_every_query_has_a_twin_or_is_known_not_to():
    own = catalogue.queries()
    assert set(own) - set(catalogue.oracle_sql()) == {"approx_distinct_hashes"}
    assert set(own) <= set(__spark_entry__.queries())


def test_sketches_are_near(spark):
    r = tables.approx_distinct_hashes(spark, SF).first()
    assert abs(r["approx"] - r["exact"]) <= 0.06 * r["exact"] + 1 and abs(r["sketch"] - r["exact"]) <= 0.06 * r["exact"] + 1


CHECKED = """raster_scan_part raster_activity_events raster_ledger_lineitem raster_bigram_documents box_downsample_documents
phash_literal_embeddings phash_ac_part phash_median_documents phash256_documents ahash_part overlap_official_part
overlap_augmented_part overlap_train_in_augmented_val dedup_components_part sanitize_report_part sanitize_three_way_part
compare_hashes_part collision_precision_part depth_ablation_documents flat_audit_ledger memorization_gap_documents
near_matches_tau2_part ops_ablation radiometric_invariance join_asof_events_orders join_interval_events window_range_7d_orders
grouping_sets_quality stream_session_events stream_dedup_events udtf_orientations sql_leakage_report""".split()


def same(value):
    return float(f"{value:.9g}") if isinstance(value, float) and not math.isnan(value) else value


@pytest.mark.parametrize("name", CHECKED)
def test_query_is_its_sql_twin(spark, duck, name):
    df = catalogue.queries()[name](spark, SF)
    result = duck.execute(catalogue.oracle_sql()[name])
    names = [c[0] for c in result.description]
    assert sorted(names) == sorted(df.columns)
    want = sorted((tuple(same(dict(zip(names, r))[c]) for c in df.columns) for r in result.fetchall()), key=repr)
    assert sorted((tuple(same(v) for v in r) for r in df.collect()), key=repr) == want


def test_string_hash_is_hex(spark):
    r = audits.hashes(spark, SF, "pages").select(hash_hex(F.col("hash")).alias("x")).first()
    assert len(r["x"]) == 16
