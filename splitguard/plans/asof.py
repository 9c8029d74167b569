"""As-of and interval joins as equi joins and windows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of_join(
    left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, values: list[str]
) -> DataFrame:
    """left with the values of the last row of right at or before it, by key; nulls if there is none.

    Both sides are put in one ordered stream a key and the last seen right row is carried
    forward, so no pair is formed. Of right rows at one time the one with the greatest values wins.
    """
    carried = F.struct(*[F.col(v) for v in values])
    one = right.select(key, F.col(right_ts).alias("__t"), carried.alias("__v"), F.lit(0).alias("__side"))
    two = left.select(
        key, F.col(left_ts).alias("__t"), F.lit(None).cast(one.schema["__v"].dataType).alias("__v"), F.lit(1).alias("__side"), F.struct("*").alias("__row")
    )
    both = two.unionByName(one, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy("__t", "__side", "__v").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last("__v", ignorenulls=True).over(w)
    found = both.withColumn("__last", last).where("__side = 1")
    return found.select("__row.*", *[F.col(f"__last.{v}").alias(v) for v in values])


def interval_join(
    left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, seconds: int
) -> DataFrame:
    """Pairs with left_ts <= right_ts <= left_ts + seconds, by key and time bucket of that width."""

    def bucket(name: str):
        return F.floor(F.unix_timestamp(F.col(name).cast("timestamp")) / seconds)

    near = left.withColumn("__b", F.explode(F.array(bucket(left_ts), bucket(left_ts) + 1)))
    other = right.withColumn("__b", bucket(right_ts))
    span = F.make_dt_interval(secs=F.lit(seconds))
    joined = near.join(other, [key, "__b"])
    return joined.where(
        (F.col(right_ts) >= F.col(left_ts)) & (F.col(right_ts) <= F.col(left_ts) + span)
    ).drop("__b")
