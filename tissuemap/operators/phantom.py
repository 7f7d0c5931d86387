"""Digital phantom, insert phantom, coil maps, field bins: all from integer ranges."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Tissue constants by class: T1, T2 in ms and density (fixed values).
CLASSES = ((0, 2600.0, 330.0, 1.00), (1, 830.0, 85.0, 0.86), (2, 500.0, 70.0, 0.77), (3, 900.0, 50.0, 0.95), (4, 350.0, 70.0, 0.90))
#: Ellipses from the outside in: class, centre x, centre y, half axes.
ELLIPSES = ((4, 0.0, 0.0, 0.72, 0.92), (0, 0.0, 0.0, 0.66, 0.85), (3, 0.0, 0.0, 0.60, 0.78), (2, 0.0, 0.0, 0.46, 0.62), (0, -0.18, -0.05, 0.10, 0.28), (0, 0.18, -0.05, 0.10, 0.28), (1, 0.0, 0.42, 0.14, 0.12))


def pixels(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n * n).select(F.floor(F.col("id") / n).cast("int").alias("row"), (F.col("id") % n).cast("int").alias("col"))


def class_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(CLASSES), "class int, t1 double, t2 double, pd double")


def digital(spark: SparkSession, n: int) -> DataFrame:
    """row, col, class, t1, t2, pd, mask: nested ellipses of five tissue classes."""
    x, y = (F.col("col") + 0.5) * 2 / n - 1, (F.col("row") + 0.5) * 2 / n - 1
    kind = F.lit(None).cast("int")
    for c, cx, cy, ax, ay in ELLIPSES:
        kind = F.when(((x - cx) / ax) ** 2 + ((y - cy) / ay) ** 2 <= 1, F.lit(c)).otherwise(kind)
    out = pixels(spark, n).withColumn("class", kind).join(F.broadcast(class_table(spark)), "class", "left")
    zero = lambda c: F.coalesce(c, F.lit(0.0)).alias(c)
    return out.select("row", "col", "class", zero("t1"), zero("t2"), zero("pd"), F.col("class").isNotNull().alias("mask"))


def resample_nn(df: DataFrame, n_from: int, n_to: int) -> DataFrame:
    """Nearest-neighbour resampling of a square grid."""
    pick = lambda c: F.floor((F.col(c) + 0.5) * n_from / n_to).cast("int")
    want = pixels(df.sparkSession, n_to).select(F.col("row").alias("_r"), F.col("col").alias("_c"), pick("row").alias("row"), pick("col").alias("col"))
    rest = [c for c in df.columns if c not in ("row", "col")]
    return want.join(df, ["row", "col"]).select(F.col("_r").alias("row"), F.col("_c").alias("col"), *rest)


def inserts(spark: SparkSession, nation: DataFrame, n: int) -> DataFrame:
    """row, col, n_nationkey, roi_id, t1, t2, pd: 25 discs on a 5 x 5 lattice in
    water; the disc's region is its region of interest.

    Each disc is looked up by its lattice cell, so no distance is compared with
    more than one disc.
    """
    cell = n / 5
    disc = nation.select(
        "n_nationkey", F.col("n_regionkey").alias("roi_id"), F.floor(F.col("n_nationkey") / 5).cast("int").alias("i"), (F.col("n_nationkey") % 5).cast("int").alias("j"),
        (200.0 + 90.0 * F.col("n_nationkey")).alias("d1"), (20.0 + 12.0 * F.col("n_nationkey")).alias("d2"),
    )
    p = pixels(spark, n).withColumns({"i": F.floor((F.col("row") + 0.5) / cell).cast("int"), "j": F.floor((F.col("col") + 0.5) / cell).cast("int")})
    out = p.join(F.broadcast(disc), ["i", "j"], "left")
    far = F.hypot(F.col("row") + 0.5 - (F.col("i") + 0.5) * cell, F.col("col") + 0.5 - (F.col("j") + 0.5) * cell)
    inside = F.coalesce(far < 0.38 * cell, F.lit(False)) & F.col("n_nationkey").isNotNull()
    own = lambda c, other: F.when(inside, F.col(c)).otherwise(F.lit(other))
    return out.select("row", "col", own("n_nationkey", None).alias("n_nationkey"), own("roi_id", None).alias("roi_id"), own("d1", 2600.0).alias("t1"), own("d2", 330.0).alias("t2"), F.lit(1.0).alias("pd"))


def coils(spark: SparkSession, n: int, count: int = 5) -> DataFrame:
    """coil, row, col, re, im: smooth maps around the head, squares summing to 1."""
    from pyspark.sql import Window

    c = spark.range(count).select(F.col("id").cast("int").alias("coil"))
    x, y = (F.col("col") + 0.5) * 2 / n - 1, (F.col("row") + 0.5) * 2 / n - 1
    angle = F.col("coil") * (2 * math.pi / count)
    near = F.exp(-((x - F.cos(angle)) ** 2 + (y - F.sin(angle)) ** 2) / 1.5)
    phase = angle + 0.5 * x * F.cos(angle)
    out = pixels(spark, n).crossJoin(F.broadcast(c)).select("coil", "row", "col", near.alias("a"), phase.alias("p"))
    total = F.sqrt(F.sum(F.col("a") ** 2).over(Window.partitionBy("row", "col")))
    return out.select("coil", "row", "col", (F.col("a") / total * F.cos("p")).alias("re"), (F.col("a") / total * F.sin("p")).alias("im"))


def field_bins(spark: SparkSession, n: int, bins: int = 7) -> DataFrame:
    """row, col, b1_bin from 1: vertical bands of transmit field strength."""
    return pixels(spark, n).select("row", "col", (F.floor(F.col("col") * bins / n) + 1).cast("int").alias("b1_bin"))


def field_factor(b: int, bins: int = 7) -> float:
    """Relative flip angle of a band: 0.85 to 1.15."""
    return 0.85 + 0.3 * (b - 1) / (bins - 1)
