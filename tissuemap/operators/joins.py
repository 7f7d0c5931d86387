"""Joins that Spark has no keyword for, as equi-joins and windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """``left`` with the ``value`` of the latest ``right`` row at or before its
    time, per key: both sides in one sorted window, no pairs are made."""
    l = left.withColumns({"_side": F.lit(1), "_v": F.lit(None).cast(right.schema[value].dataType)})
    r = right.select(key, time, F.col(value).alias("_v")).withColumn("_side", F.lit(0))
    both = r.unionByName(l, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last("_v", ignorenulls=True).over(w)).filter("_side = 1").select(*[c for c in left.columns if c != value], value)


def in_bins(points: DataFrame, bins: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Points within [low, high): each bin is spread over grid cells of ``width``,
    and points meet only the bins of their own cell."""
    spread = bins.withColumn("_c", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    p = points.withColumn("_c", F.floor(F.col(value) / width))
    return p.join(spread, "_c").filter((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("_c")


def within(left: DataFrame, right: DataFrame, key: str, seconds: int, lt: str, rt: str) -> DataFrame:
    """Pairs per key with 0 < rt - lt <= seconds: equal or next time bucket."""
    bucket = lambda c: F.floor(F.unix_micros(c) / (seconds * 1_000_000))
    l = left.withColumn("_b", F.explode(F.array(bucket(F.col(lt)), bucket(F.col(lt)) + 1)))
    r = right.withColumn("_b", bucket(F.col(rt)))
    gap = F.unix_micros(F.col(rt)) - F.unix_micros(F.col(lt))
    return l.join(r, [key, "_b"]).filter((gap > 0) & (gap <= seconds * 1_000_000)).drop("_b")


def salted_sum(df: DataFrame, key: str, value: Column, salts: int = 16) -> DataFrame:
    """Sum per key in two rounds, so that a hot key is shared by many tasks."""
    part = df.withColumn("_s", F.pmod(F.xxhash64(*df.columns), F.lit(salts))).groupBy(key, "_s").agg(F.sum(value).alias("v"))
    return part.groupBy(key).agg(F.sum("v").alias("v"))


def rollup_errors(df: DataFrame, keys: list[str], value: str) -> DataFrame:
    return df.rollup(*keys).agg(F.grouping_id().alias("gid"), F.avg(value).alias("mean"), F.count("*").alias("n"))
