"""Step-size rules over image and sample tables: one aggregate, one row each."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def rescale(samples: DataFrame, predicted: DataFrame, keys: list[str]) -> DataFrame:
    """slice_id, step: Re<y, A x> / |A x|^2, which minimises |step * A x - y|^2."""
    p = predicted.select(*keys, F.col("re").alias("pr"), F.col("im").alias("pi"))
    s = samples.join(p, keys).groupBy("slice_id")
    return s.agg((F.sum(F.col("re") * F.col("pr") + F.col("im") * F.col("pi")) / F.sum(F.col("pr") ** 2 + F.col("pi") ** 2)).alias("step"))


def _power(df: DataFrame, name: str) -> DataFrame:
    return df.groupBy("slice_id").agg(F.sum(F.col("re") ** 2 + F.col("im") ** 2).alias(name))


def difference(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    other = b.select(*keys, F.col("re").alias("_r"), F.col("im").alias("_i"))
    return a.join(other, keys).select(*keys, (F.col("re") - F.col("_r")).alias("re"), (F.col("im") - F.col("_i")).alias("im"))


def cond_a(delta: DataFrame, image_of_delta: DataFrame, step: float, slack: float = 0.99) -> DataFrame:
    """slice_id, bound, passes: the step against the curvature met on the way.
    ``image_of_delta`` is the normal operator's (or forward operator's) result."""
    out = _power(delta, "moved").join(_power(image_of_delta, "curved"), "slice_id")
    return out.select("slice_id", (slack * F.col("moved") / F.col("curved")).alias("bound")).withColumn("passes", F.lit(step) <= F.col("bound"))


def cond_b(before: DataFrame, after: DataFrame, rule: str = "decrease") -> DataFrame:
    """slice_id, before, after, passes: the normal-equation residual must not
    grow; ``as_printed`` has the inequality the other way round."""
    out = _power(before, "before").join(_power(after, "after"), "slice_id")
    good = F.col("after") <= F.col("before") if rule == "decrease" else F.col("after") >= F.col("before")
    return out.withColumn("passes", good)


def undersampling_ratio(samples: DataFrame, n: int) -> DataFrame:
    """slice_id, step: voxels over samples per readout."""
    per = samples.groupBy("slice_id", "coil", "t").agg(F.count("*").alias("m"))
    return per.groupBy("slice_id").agg((F.lit(float(n * n)) / F.avg("m")).alias("step"))
