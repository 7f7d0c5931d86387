"""Readers of the given tables and the matrices made of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .schemas import TABLES, schema


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table under its declared schema, so that no footer is read to plan."""
    return spark.read.schema(schema(TABLES[name])).parquet(f"{sf_dir}/{name}.parquet")


def month(ts: Column) -> Column:
    """Months since January 1995."""
    return ((F.year(ts) - 1995) * 12 + F.month(ts) - 1).cast("int")


def sales_matrix(spark: SparkSession, sf_dir: str, width: int = 50) -> DataFrame:
    """Part grid by month: voxel, row, col, t, v. An undersampled matrix."""
    li = read(spark, sf_dir, "lineitem").select("l_partkey", "l_shipdate", "l_extendedprice", "l_discount")
    out = li.groupBy(F.col("l_partkey").alias("voxel"), month(F.col("l_shipdate")).alias("t"))
    out = out.agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v"))
    return out.select("voxel", F.floor(F.col("voxel") / width).cast("int").alias("row"), (F.col("voxel") % width).cast("int").alias("col"), "t", "v")


def supplier_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supplier by month: voxel, t, v. Almost fully sampled."""
    li = read(spark, sf_dir, "lineitem").select("l_suppkey", "l_shipdate", "l_extendedprice", "l_discount")
    out = li.groupBy(F.col("l_suppkey").alias("voxel"), month(F.col("l_shipdate")).alias("t"))
    return out.agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v"))


def orders_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = read(spark, sf_dir, "orders").select("o_custkey", "o_orderdate", "o_totalprice")
    return o.groupBy(F.col("o_custkey").alias("voxel"), month(F.col("o_orderdate")).alias("t")).agg(F.sum("o_totalprice").alias("v"))


def vectors(spark: SparkSession, sf_dir: str, odd: bool) -> DataFrame:
    """Odd embeddings as voxels, even ones as atoms: id, label, x array<double>."""
    e = read(spark, sf_dir, "embeddings").filter(F.col("vec_id") % 2 == int(odd))
    return e.select(F.col("vec_id").alias("id"), "label", F.transform("embedding", lambda v: v.cast("double")).alias("x"))


def pack(long: DataFrame, keys: list[str], index: str, *values: str) -> DataFrame:
    """One row per key with its values as an array in order of ``index``."""
    item = F.struct(index, *values)
    out = long.groupBy(*keys).agg(F.sort_array(F.collect_list(item)).alias("p"))
    value = (lambda x: x[values[0]]) if len(values) == 1 else (lambda x: F.struct(*[x[v].alias(v) for v in values]))
    return out.select(*keys, F.transform("p", value).alias("sig"))


def unpack(packed: DataFrame, keys: list[str], index: str = "t", value: str = "v") -> DataFrame:
    return packed.select(*keys, F.posexplode("sig").alias(index, value))


def stream_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events`` as readouts: event_id, ts, slice, coil, cell, value."""
    e = read(spark, sf_dir, "events")
    return acquisition(e)


def acquisition(events: DataFrame) -> DataFrame:
    return events.select(
        "event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("slice"), F.col("event_type").alias("coil"),
        F.from_json("props", "k int")["k"].alias("cell"), "value",
    )
