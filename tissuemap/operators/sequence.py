"""Pulse schedule, spiral trajectory and its Cartesian sampling mask."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Echo and inversion times in ms (fixed values).
TE, TI = 2.0, 21.0
LOBE, TR_PERIOD = 25, 37
TURN, LATE_TURN, INTERLEAVES = 82.5, 84.0, 48


def pulse_schedule(spark: SparkSession, length: int) -> DataFrame:
    """t, tr_ms in [12.1, 15], fa_deg in [0, 74]: half-sine lobes of changing
    height. The schedule of a shorter scan is a prefix of that of a longer one."""
    return pulses(spark.range(length).select(F.col("id").cast("int").alias("t")))


def pulses(times: DataFrame) -> DataFrame:
    """The pulse of each time point ``t`` of ``times``: t, tr_ms, fa_deg."""
    t = F.col("t")
    lobe = F.floor(t / LOBE)
    height = 0.3 + 0.7 * F.abs(F.sin(1.7 * lobe + 0.6))
    return times.select(
        "t",
        (13.55 + 1.45 * F.sin(2 * math.pi * t / TR_PERIOD)).alias("tr_ms"),
        (74.0 * height * F.sin(math.pi * (t % LOBE) / LOBE)).alias("fa_deg"),
    )


def spiral_angles(spark: SparkSession, length: int) -> DataFrame:
    """t, angle in degrees: a turn of 82.5, and 84 at each 48th repetition."""
    return angles(spark.range(length).select(F.col("id").cast("int").alias("t")))


def angles(times: DataFrame) -> DataFrame:
    """The angle of each repetition ``t`` of ``times``: t, angle."""
    t = F.col("t")
    late = F.floor(t / INTERLEAVES)
    angle = (t - late) * TURN + late * LATE_TURN
    return times.select("t", (angle - 360.0 * F.floor(angle / 360.0)).alias("angle"))


def spiral(spark: SparkSession, length: int, n: int, samples: int, inner: float = 24.0, outer: float = 48.0) -> DataFrame:
    """t, sample_no, kx, ky of variable-density interleaves.

    The gap between turns grows linearly from ``inner`` to ``outer`` cells, which
    makes the radius an exponential of the angle.
    """
    return interleaves(spiral_angles(spark, length), n, samples, inner, outer)


def interleaves(turned: DataFrame, n: int, samples: int, inner: float = 24.0, outer: float = 48.0) -> DataFrame:
    """The points of one interleaf for each row (t, angle) of ``turned``."""
    edge = n / 2 - 0.5
    grow = (outer - inner) / edge / (2 * math.pi)
    last = math.log(1 + grow * edge * 2 * math.pi / inner) / grow
    s = F.col("s")
    winding = F.sqrt((s + 0.5) / samples) * last
    radius = inner / (2 * math.pi * grow) * (F.exp(grow * winding) - 1)
    turn = winding + F.radians("angle")
    points = turned.sparkSession.range(samples).select(F.col("id").cast("int").alias("s"))
    return turned.crossJoin(F.broadcast(points)).select(
        "t", F.col("s").alias("sample_no"), (radius * F.cos(turn)).alias("kx"), (radius * F.sin(turn)).alias("ky")
    )


def sampling_mask(trajectory: DataFrame, n: int) -> DataFrame:
    """t, ku, kv, w: the frequency cells that each interleaf meets, once each.

    Cells are 0..n-1 in transform order. The weight compensates density: the
    number of repetitions over how many of them meet the cell.
    """
    cell = lambda c: F.pmod(F.round(c).cast("int"), F.lit(n))
    hit = trajectory.select("t", cell(F.col("kx")).alias("ku"), cell(F.col("ky")).alias("kv")).dropDuplicates()
    count = hit.groupBy("ku", "kv").agg(F.count("*").alias("met"))
    total = trajectory.agg((F.max("t") + 1).alias("length"))
    return hit.join(count, ["ku", "kv"]).crossJoin(F.broadcast(total)).select("t", "ku", "kv", (F.col("length") / F.col("met")).alias("w"))
