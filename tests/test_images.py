"""Images made of keys: the numpy kernels against the expressions of Spark, and their plan."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from splitguard.operators import raster
from splitguard.plans import images

SF = "/root/testdata/sf0.001"
QUERIES = ["grey_modes_images", "fit_images", "phash_images", "phash_factor_images", "wrong_sizes_images"]


@pytest.mark.parametrize("name", QUERIES)
def test_cells_never_pass_through_spark(spark, name):
    """One kernel a query, fed with keys that are dealt out over all tasks."""
    plan = images.entries()[name][0](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == 1 and "transform(" not in plan and "REPARTITION_BY_NUM" in plan


def test_index_size_makes_its_images_once(spark):
    assert "MapInArrow" not in images.index_size_images(spark, SF)._jdf.queryExecution().toString()


def test_grey_lists_are_to_grey(spark):
    rows = [([0, 255, 7, None], [255, 3, 9, 1], [1, 2, 3, 4]), ([], [], []), (None, None, None), ([8], [9], [12])]
    cells = [pa.array([r[i] for r in rows], pa.list_(pa.int32())) for i in range(3)]
    table = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "i int, r array<int>, g array<int>, b array<int>")
    for mode in ("luma", "mean", "green"):
        grey = raster.to_grey(F.col("r"), F.col("g"), F.col("b"), mode)
        made = table.select(grey.alias("p"), F.array_join(grey.cast("array<string>"), ",").alias("t"), "i").orderBy("i").collect()
        got = raster.grey_lists(*cells, mode)
        assert got.to_pylist() == [r["p"] for r in made]
        assert raster.joined_lists(got).to_pylist() == [r["t"] for r in made]
    wide = pa.array([[-5, 1 << 20], [3]], pa.list_(pa.int32()))
    assert raster.joined_lists(wide).to_pylist() == ["-5,1048576", "3"]


def test_colour_cells_by_hand():
    keys = np.array([0, 1, 19, 2**40 + 3, -7])
    for a, b, c in images._COLOURS.values():
        for n in (keys, keys[:4]):
            got = images.colour_cells(n, a, b, c)
            for i, key in enumerate(n.tolist()):
                whole = [k * a + key * b + (k // 40) * int(np.fmod(key, c)) for k in (0, 39, 40, 1919)]
                assert got[i, [0, 39, 40, 1919]].tolist() == [int(np.fmod(x, 256)) for x in whole]


def test_a_part_without_a_key(spark, tmp_path):
    spark.createDataFrame([(None,), (1,), (10,)], "p_partkey long").write.parquet(f"{tmp_path}/part.parquet")
    got = {r["image_id"]: r for r in images.fit_images(spark, str(tmp_path)).collect()}
    assert got[None]["reason"] == "null pixel" and got[10]["cells"] is None and got[1]["cells"].count(",") == 1023
    counts = {r["what"]: r["n"] for r in images.wrong_sizes_images(spark, str(tmp_path)).collect()}
    assert counts == {"null pixel": 1, "whole": 1, "smaller than the target": 1, "hashed": 1}
