"""Spatial regularisation on image tables: slice_id, comp, row, col, re, im.

Differences are windows along rows and columns; missing neighbours are zero at
the far border. Real images have im = 0.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def _lines() -> tuple:
    """Windows down the columns and along the rows of an image."""
    return Window.partitionBy("slice_id", "comp", "col").orderBy("row"), Window.partitionBy("slice_id", "comp", "row").orderBy("col")


def grad(img: DataFrame) -> DataFrame:
    """Adds forward differences dre_r, dim_r (down) and dre_c, dim_c (right)."""
    down, right = _lines()
    step = lambda c, w: F.coalesce(F.lead(c).over(w) - F.col(c), F.lit(0.0))
    return img.withColumns({"dre_r": step("re", down), "dim_r": step("im", down)}).withColumns({"dre_c": step("re", right), "dim_c": step("im", right)})


def div(field: DataFrame) -> DataFrame:
    """Minus the adjoint of :func:`grad`, of columns pr_r, pi_r, pr_c, pi_c.

    A border value of the field meets no difference, so it counts as zero.
    """

    def part(c: str, w) -> Column:
        own = F.when(F.lead(F.lit(1)).over(w).isNotNull(), F.col(c)).otherwise(F.lit(0.0))
        return own - F.coalesce(F.lag(c).over(w), F.lit(0.0))

    down, right = _lines()
    out = field.withColumns({"_a": part("pr_r", down), "_b": part("pi_r", down)}).withColumns({"_c": part("pr_c", right), "_d": part("pi_c", right)})
    return out.withColumns({"dre": F.col("_a") + F.col("_c"), "dim": F.col("_b") + F.col("_d")}).drop("_a", "_b", "_c", "_d")


def _length(names: list[str]):
    total = F.lit(0.0)
    for c in names:
        total = total + F.col(c) * F.col(c)
    return F.sqrt(total)


def tv(img: DataFrame, joint: bool = False) -> DataFrame:
    """slice_id, comp, tv: isotropic total variation; ``joint`` couples the
    components of a voxel and returns one value per slice (comp null)."""
    names = ["dre_r", "dim_r", "dre_c", "dim_c"]
    g = grad(img)
    if joint:
        length = F.sqrt(F.sum(_length(names) ** 2))
        return g.groupBy("slice_id", "row", "col").agg(length.alias("v")).groupBy("slice_id").agg(F.lit(None).cast("int").alias("comp"), F.sum("v").alias("tv"))
    return g.groupBy("slice_id", "comp").agg(F.sum(_length(names)).alias("tv"))


def tv_prox(img: DataFrame, s: float, iters: int = 5, complex_mode: str = "joint", joint: bool = False, tau: float = 0.125) -> DataFrame:
    """Proximal map of s times the total variation by dual projection.

    Unrolled window stages: for the small grids of tests, or for images beyond a
    task's memory; slices otherwise use the array kernel.
    """
    if s == 0:
        return img
    names = ["pr_r", "pi_r", "pr_c", "pi_c"]
    state = img.select("slice_id", "comp", "row", "col", F.col("re").alias("zr"), F.col("im").alias("zi")).withColumns({c: F.lit(0.0) for c in names})
    for _ in range(iters):
        d = div(state)
        q = grad(d.withColumns({"re": F.col("dre") - F.col("zr") / s, "im": F.col("dim") - F.col("zi") / s}))
        step = {"pr_r": "dre_r", "pi_r": "dim_r", "pr_c": "dre_c", "pi_c": "dim_c"}
        if complex_mode == "split":
            lengths = {c: _length(["dre_r", "dre_c"] if c[1] == "r" else ["dim_r", "dim_c"]) for c in names}
        else:
            whole = _length(list(step.values()))
            if joint:
                whole = F.sqrt(F.sum(whole**2).over(Window.partitionBy("slice_id", "row", "col")))
            lengths = dict.fromkeys(names, whole)
        q = q.withColumns({f"_{c}": (F.col(c) + tau * F.col(step[c])) / (1 + tau * lengths[c]) for c in names})
        state = q.select("slice_id", "comp", "row", "col", "zr", "zi", *[F.col(f"_{c}").alias(c) for c in names])
    out = div(state)
    return out.select("slice_id", "comp", "row", "col", (F.col("zr") - s * F.col("dre")).alias("re"), (F.col("zi") - s * F.col("dim")).alias("im"))


def cycle_spin(img: DataFrame, n: int, s: float, shifts: int = 2) -> DataFrame:
    """One level of 2 x 2 Haar detail soft-thresholded by s, averaged over
    ``shifts`` x ``shifts`` circular shifts."""
    spark = img.sparkSession
    moves = spark.range(shifts * shifts).select(F.floor(F.col("id") / shifts).alias("sr"), (F.col("id") % shifts).alias("sc"))
    m = img.crossJoin(F.broadcast(moves))
    m = m.withColumns({"r": F.pmod(F.col("row") + F.col("sr"), F.lit(n)), "c": F.pmod(F.col("col") + F.col("sc"), F.lit(n))})
    w = Window.partitionBy("slice_id", "comp", "sr", "sc", F.floor(F.col("r") / 2), F.floor(F.col("c") / 2))
    a, b = F.when(F.col("r") % 2 == 0, 1.0).otherwise(-1.0), F.when(F.col("c") % 2 == 0, 1.0).otherwise(-1.0)
    out = {}
    for part in ("re", "im"):
        value = F.sum(part).over(w) / 4
        for sign in (a, b, a * b):
            d = F.sum(F.col(part) * sign).over(w) / 2
            value = value + sign * F.signum(d) * F.greatest(F.abs(d) - s, F.lit(0.0)) / 2
        out[f"_{part}"] = value
    m = m.withColumns(out)
    return m.groupBy("slice_id", "comp", "row", "col").agg(F.avg("_re").alias("re"), F.avg("_im").alias("im"))


def low_pass(img: DataFrame, n: int, radius: float) -> DataFrame:
    """Keep frequencies within ``radius`` cells of zero."""
    from .encode import image, spectrum

    keys = ["slice_id", "comp"]
    far = lambda c: F.least(F.col(c), n - F.col(c))
    return image(spectrum(img, n, keys).filter(far("ku") ** 2 + far("kv") ** 2 <= radius**2), n, keys)


def identity(img: DataFrame) -> DataFrame:
    return img


def neighbour_differences(img: DataFrame) -> DataFrame:
    """Differences to the lower neighbour by a self-join on the shifted key."""
    below = img.select("slice_id", "comp", (F.col("row") - 1).alias("row"), "col", F.col("re").alias("next"))
    return img.join(below, ["slice_id", "comp", "row", "col"], "left").withColumn("dre_r", F.coalesce(F.col("next") - F.col("re"), F.lit(0.0)))
