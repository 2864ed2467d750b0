"""Joins that Spark has no operator for, composed of those it has."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def salted_join(left: DataFrame, right: DataFrame, left_key: str, right_key: str, salts: int) -> DataFrame:
    """Inner join with every key dealt over ``salts`` parts: for left keys too frequent for one task.

    The right side is repeated ``salts`` times, so it should be the smaller one.
    """
    dealt = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    repeated = right.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    on = (F.col(left_key) == F.col(right_key)) & (dealt["__salt"] == repeated["__salt"])
    return dealt.join(repeated, on).drop("__salt")


def interval_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of a key whose right time lies before the left time by ``seconds`` at most.

    Both times are cut into buckets of that length; a left row meets its own and the
    previous bucket, so the join is an equi-join and the range only filters.
    """
    number = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    width = seconds * 1_000_000
    bucket = lambda c: F.floor(number(c) / width)
    near = left.withColumn("__b", F.explode(F.array(bucket(left_time), bucket(left_time) - 1)))
    far = right.withColumn("__b", bucket(right_time))
    gap = number(left_time) - number(right_time)
    return near.join(far, [key, "__b"]).where((gap > 0) & (gap <= width)).drop("__b")


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """Left rows with the value of the latest strictly earlier right row of their key (null if none).

    One union, one shuffle by key, one running window; equal times do not match, and of
    several right rows of one time the largest value counts.
    """
    rest = [c for c in left.columns if c not in (key, time)]
    events = right.select(key, time, F.col(value).alias("__v"), *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in rest], F.lit(1).alias("__side"))
    asked = left.select(key, time, F.lit(None).cast(right.schema[value].dataType).alias("__v"), *rest, F.lit(0).alias("__side"))
    order = Window.partitionBy(key).orderBy(time, "__side", F.col("__v").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    both = asked.unionByName(events).withColumn(value, F.last("__v", ignorenulls=True).over(order))
    return both.where("__side = 0").select(key, time, *rest, value)
