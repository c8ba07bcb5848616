"""Relational helpers around the methods: as-of, interval and range joins, Spark-first."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def micros(time: str | Column) -> Column:
    """Microseconds of a timestamp with or without zone (UTC sessions)."""
    return F.unix_micros((F.col(time) if isinstance(time, str) else time).cast("timestamp"))


def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """left plus <value>_asof: the value of the latest right row of the key at or before the left row's time.

    One exchange on the key: both sides are unioned, and a running last value passes over them; at equal times right
    rows count as earlier, and of equal right times the largest value wins.
    """
    cols = left.columns
    a = left.select(*cols, F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"))
    b = right.select(*[F.col(c) if c in (key, time) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in cols], F.col(value).alias("_v"), F.lit(0).alias("_side"))
    w = Window.partitionBy(key).orderBy(time, "_side", F.col("_v").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    out = a.unionByName(b).withColumn(f"{value}_asof", F.last("_v", ignorenulls=True).over(w))
    return out.filter("_side = 1").select(*cols, f"{value}_asof")


def interval_join(left: DataFrame, right: DataFrame, key: str, time: str, seconds: int) -> DataFrame:
    """Pairs of a key whose right time lies in (left time, left time + seconds].

    The time is cut into buckets of that length, so a left row meets two buckets only and the join is an equi-join.
    """
    bucket = F.floor(micros(time) / (seconds * 1_000_000))
    a = left.withColumn("_b", F.explode(F.array(bucket, bucket + 1)))
    b = right.select(key, F.col(time).alias("_t"), *[F.col(c).alias(f"{c}_r") for c in right.columns if c not in (key, time)], bucket.alias("_b"))
    gap = micros("_t") - micros(time)
    return a.join(b, [key, "_b"]).filter((gap > 0) & (gap <= seconds * 1_000_000)).drop("_b").withColumnRenamed("_t", f"{time}_r")


def range_join(points: DataFrame, value: str, bands: DataFrame, low: str, high: str) -> DataFrame:
    """points with the bands [low, high) that hold them; bands is a small dimension (it is broadcast after a count)."""
    if bands.count() > 100_000:
        raise ValueError("too many bands to broadcast; bucket the range instead")
    return points.join(F.broadcast(bands), (F.col(value) >= F.col(low)) & (F.col(value) < F.col(high)))


def sessionize(events: DataFrame, key: str, time: str, gap_seconds: int) -> DataFrame:
    """events plus session (from 1): a gap of more than gap_seconds begins a new one."""
    w = Window.partitionBy(key).orderBy(time, *[c for c in events.columns if c not in (key, time)][:1])
    new = (micros(time) - micros(F.lag(time).over(w)) > gap_seconds * 1_000_000).cast("int")
    return events.withColumn("session", F.sum(F.coalesce(new, F.lit(0))).over(w) + 1)
