"""Arrival guard and windowed duplicate rates on streams.

Event times of the tables carry no zone; they are read as UTC timestamps, since
watermarks need that type. Every query here ends by itself with `availableNow`.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from splitguard.functions.runtime import ensure_checkpoint_dir
from splitguard.operators.fingerprint import phash
from splitguard.operators.raster import with_split


def table_stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table as a stream: all files of its folder, or its one file.

    A file source watches a folder, so of a table in one file the folder around it is watched
    with a filter on the name. Such a filter holds for the names of files, so it would leave
    nothing of a table that is a folder itself.
    """
    place = f"{sf_dir}/{name}.parquet"
    path = spark._jvm.org.apache.hadoop.fs.Path(place)
    files = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    source = spark.readStream.schema(spark.read.parquet(place).schema)
    if files.getFileStatus(path).isDirectory():
        return source.parquet(place)
    return source.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream, with ts as a timestamp."""
    return table_stream(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is available now, with checkpointed state, and read its result.

    Results go to Parquet in the shared folder, a folder a micro-batch, and never to the driver.
    The last complete result counts, or all appended or updated rows.
    """
    spark = stream.sparkSession
    base = f"{ensure_checkpoint_dir(spark)}/stream-{uuid.uuid4().hex}"
    batches: list[str] = []

    def keep(batch: DataFrame, number: int) -> None:
        path = f"{base}/rows/{number}"
        batch.write.mode("overwrite").parquet(path)  # a batch that is run again replaces itself
        batches.append(path)

    query = (
        stream.writeStream.foreachBatch(keep)
        .outputMode(mode)
        .option("checkpointLocation", f"{base}/state")
        .trigger(availableNow=True)
        .start()
    )
    query.awaitTermination()
    if not batches:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*(batches[-1:] if mode == "complete" else sorted(set(batches))))


def run_to_parquet(stream: DataFrame, path: str, checkpoint: str) -> None:
    """Append a stream's rows to Parquet; a second run goes on from the checkpoint."""
    query = (
        stream.writeStream.format("parquet")
        .option("path", path)
        .option("checkpointLocation", checkpoint)
        .trigger(availableNow=True)
        .start()
    )
    query.awaitTermination()


def run_per_batch(stream: DataFrame, handle, checkpoint: str) -> None:
    """Give each micro-batch to handle(batch, number)."""
    query = (
        stream.writeStream.foreachBatch(handle)
        .option("checkpointLocation", checkpoint)
        .trigger(availableNow=True)
        .start()
    )
    query.awaitTermination()


def tumbling_counts(events: DataFrame, size: str = "6 hours", late: str = "1 day") -> DataFrame:
    return (
        events.withWatermark("ts", late)
        .groupBy(F.window("ts", size).alias("w"), "event_type")
        .agg(F.count(F.lit(1)).alias("n"))
        .select(F.col("w.start").alias("start"), "event_type", "n")
    )


def sliding_counts(events: DataFrame, size: str = "1 day", step: str = "6 hours", late: str = "1 day") -> DataFrame:
    return (
        events.withWatermark("ts", late)
        .groupBy(F.window("ts", size, step).alias("w"))
        .agg(F.count(F.lit(1)).alias("n"))
        .select(F.col("w.start").alias("start"), "n")
    )


def session_counts(events: DataFrame, gap: str = "8 hours", late: str = "1 day") -> DataFrame:
    return (
        events.withWatermark("ts", late)
        .groupBy("user_id", F.session_window("ts", gap).alias("w"))
        .agg(F.count(F.lit(1)).alias("n"))
        .select("user_id", F.col("w.start").alias("start"), "n")
    )


def first_arrivals(events: DataFrame, key: str, late: str = "60 days") -> DataFrame:
    """The first arrival of each key; state is dropped once it is older than the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def text_stream(spark: SparkSession, sf_dir: str, name: str, key: str, text: str) -> DataFrame:
    """A table's texts as a stream of a collection (image_id, split, payload)."""
    slim = table_stream(spark, sf_dir, name).select(F.col(key).cast("long").alias("image_id"), F.col(text).alias("payload"))
    return with_split(slim).select("image_id", "split", "payload")


def leak_guard(arrivals: DataFrame, index: DataFrame) -> DataFrame:
    """arrivals (hash, ...) with `leaks`: whether the hash is in a static index."""
    known = index.select(F.col("hash").alias("known_hash")).distinct()
    joined = arrivals.join(known, arrivals["hash"] == known["known_hash"], "left")
    return joined.withColumn("leaks", F.col("known_hash").isNotNull()).drop("known_hash")


def raster_guard(arrivals: DataFrame, index: DataFrame, kind: str, threshold: str = "mean_ac") -> DataFrame:
    """(image_id, hash, leaks, known_id) of arriving rasters (image_id, split, payload): each is
    fingerprinted as it arrives and looked up in a static index (hash, min_id, ...)."""
    known = index.select(F.col("hash").alias("known_hash"), F.col("min_id").alias("known_id"))
    hashed = phash(arrivals, kind, threshold=threshold)
    joined = hashed.join(known, hashed["hash"] == known["known_hash"], "left")
    return joined.select("image_id", "hash", F.col("known_hash").isNotNull().alias("leaks"), "known_id")


def first_seen_state(events: DataFrame, key: str) -> DataFrame:
    """(key, first_ts, n) by stateful processing: how often each key has arrived so far.

    State is one small row a key.
    """
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(keys, frames, state):
        first, n = state.get if state.exists else (None, 0)
        for frame in frames:
            low = frame["ts"].min()
            first = low if first is None or low < first else first
            n += len(frame)
        state.update((first, n))
        import pandas as pd

        yield pd.DataFrame({"key": [keys[0]], "first_ts": [first], "n": [n]})

    return (
        events.select(F.col(key).cast("long").alias("key"), "ts")
        .groupBy("key")
        .applyInPandasWithState(
            update,
            "key long, first_ts timestamp, n long",
            "first_ts timestamp, n long",
            "update",
            GroupStateTimeout.NoTimeout,
        )
    )
