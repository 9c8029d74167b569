"""Session helpers: reliable checkpoints, joins on hot keys, one-evaluation bindings."""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A key is hot if it holds more rows than this and more than one in MOST_HOT of all rows.
LEAST_HOT = 1_000
#: By that share there are fewer hot keys than this, whatever the size of the table.
MOST_HOT = 100_000


def ensure_checkpoint_dir(spark: SparkSession) -> str:
    """The shared checkpoint folder of the session.

    Only a local session may do without one: its driver and executors are one process, so a
    temporary folder is shared by them. On a cluster it would be lost with its machine.
    """
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named:
            if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
            named = tempfile.mkdtemp(prefix="checkpoints-")
        sc.setCheckpointDir(named)
    return sc.getCheckpointDir()


def reliable(df: DataFrame) -> DataFrame:
    """Cut the lineage of df with an eager checkpoint in the shared folder."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def remove_folder(spark: SparkSession, path: str) -> None:
    """Delete a folder in whatever file system holds it."""
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


@contextmanager
def passing_checkpoints(spark: SparkSession, folder: str) -> Iterator[None]:
    """Checkpoints made inside go to folder, which is deleted at the end.

    For work whose result is written to a table before the end.
    """
    before = ensure_checkpoint_dir(spark)
    spark.sparkContext.setCheckpointDir(folder)
    try:
        yield
    finally:
        spark.sparkContext.setCheckpointDir(before)
        remove_folder(spark, folder)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def join_by_key(
    rows: DataFrame,
    side: DataFrame,
    keys: list[str],
    count: str = "n",
    how: str = "inner",
    most_hot: int | None = None,
) -> DataFrame:
    """rows joined, inner or left, to side: one row a key, with its number of rows in `count`.

    Hot keys are joined by broadcast, there being fewer than most_hot of them; the others
    by shuffle, where none holds more than a small share of the rows. Both frames are read
    twice, so they should be checkpointed. The count is not in the result.
    """
    total = side.agg(F.coalesce(F.sum(count), F.lit(0)).alias("n")).first()["n"]
    limit = max(LEAST_HOT, int(total) // (most_hot or MOST_HOT))
    hot = side.where(F.col(count) > limit).drop(count)
    if not hot.limit(1).count():
        return rows.join(side.drop(count), keys, how)
    marked = rows.join(F.broadcast(hot.withColumn("__hot", F.lit(True))), keys, "left")
    own = marked.where("__hot").drop("__hot")
    rest = marked.where("__hot is null").select(*rows.columns)
    light = side.where(F.col(count) <= limit).drop(count)
    return rest.join(light, keys, how).unionByName(own)


def bind(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value evaluated once per row.

    Chained selects over higher-order functions are collapsed and re-inlined
    into every lambda; a one-element array keeps the intermediate in one place.
    """
    return F.transform(F.array(value), body).getItem(0)
