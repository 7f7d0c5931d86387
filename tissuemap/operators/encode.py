"""The encode operator and its adjoint over tables of coefficients.

Order of the forward direction, all in the compressed domain: coil weights, the
unitary 2-D Fourier transform as two separable sums, then per time point the
basis row mixes the component spectra of the cells that the time point samples.
sqrt(w) stands on both sides, so that the adjoint is one.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.cx import product_sums

FLAT = ["re", "im"]


def dft(img: DataFrame, n: int, a: str, b: str, keys: list[str], inverse: bool = False) -> DataFrame:
    """Unitary transform along axis ``a``, which becomes ``b``. ``keys`` stay."""
    spark = img.sparkSession
    sign = 1 if inverse else -1
    # n x n twiddle factors: the grid's edge squared, whatever the number of slices
    axis = spark.range(n).select(F.col("id").cast("int").alias("_k"))
    place = spark.range(n).select(F.col("id").cast("int").alias("_x"))
    angle = F.col("_x") * F.col("_k") * (sign * 2 * math.pi / n)
    twiddle = place.crossJoin(axis).select("_x", "_k", (F.cos(angle) / math.sqrt(n)).alias("_c"), (F.sin(angle) / math.sqrt(n)).alias("_s"))
    re, im = product_sums(F.col("re"), F.col("im"), F.col("_c"), F.col("_s"))
    return img.join(F.broadcast(twiddle), F.col(a) == F.col("_x")).groupBy(*keys, F.col("_k").alias(b)).agg(re.alias("re"), im.alias("im"))


def spectrum(img: DataFrame, n: int, keys: list[str]) -> DataFrame:
    """keys, ku, kv, re, im from keys, row, col, re, im."""
    return dft(dft(img, n, "row", "ku", [*keys, "col"]), n, "col", "kv", [*keys, "ku"])


def spectrum_packed(img: DataFrame, n: int, keys: list[str]) -> DataFrame:
    """As :func:`spectrum` by a fast transform, one task per image: for grids
    whose n^3 products of the relational form are too many."""
    import numpy as np
    import pandas as pd

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.zeros((n, n), complex)
        x[pdf["row"], pdf["col"]] = pdf["re"] + 1j * pdf["im"]
        y = np.fft.fft2(x, norm="ortho").ravel()
        ku, kv = np.divmod(np.arange(n * n, dtype=np.int32), n)
        return pd.DataFrame({**{k: v for k, v in zip(keys, key, strict=True)}, "ku": ku, "kv": kv, "re": y.real, "im": y.imag})

    kinds = {f.name: f.dataType.simpleString() for f in img.schema}
    head = "".join(f"{k} {kinds[k]}, " for k in keys)
    return img.groupBy(*keys).applyInPandas(run, f"{head}ku int, kv int, re double, im double")


def image(spec: DataFrame, n: int, keys: list[str]) -> DataFrame:
    return dft(dft(spec, n, "ku", "row", [*keys, "kv"], True), n, "kv", "col", [*keys, "row"], True)


def coil_weighted(img: DataFrame, coils: DataFrame | None) -> DataFrame:
    """One image per coil; without maps a single coil of weight one."""
    if coils is None:
        return img.withColumn("coil", F.lit(0))
    c = coils.select("coil", "row", "col", F.col("re").alias("cr"), F.col("im").alias("ci"))
    return img.join(F.broadcast(c), ["row", "col"]).select(
        "slice_id", "coil", "row", "col", "comp", (F.col("re") * F.col("cr") - F.col("im") * F.col("ci")).alias("re"),
        (F.col("re") * F.col("ci") + F.col("im") * F.col("cr")).alias("im"),
    )


def coil_combined(img: DataFrame, coils: DataFrame | None) -> DataFrame:
    """Sum over coils with conjugated maps."""
    if coils is None:
        return img.select("slice_id", "row", "col", "comp", "re", "im")
    c = coils.select("coil", "row", "col", F.col("re").alias("cr"), F.col("im").alias("ci"))
    re, im = product_sums(F.col("re"), F.col("im"), F.col("cr"), F.col("ci"), conjugate=True)
    return img.join(F.broadcast(c), ["coil", "row", "col"]).groupBy("slice_id", "row", "col", "comp").agg(re.alias("re"), im.alias("im"))


def _basis(basis: DataFrame, comp: str = "comp") -> DataFrame:
    return F.broadcast(basis.select("t", F.col("comp").alias(comp), F.col("re").alias("br"), F.col("im").alias("bi")))


def sample(spec: DataFrame, mask: DataFrame, basis: DataFrame) -> DataFrame:
    """slice_id, coil, t, ku, kv, re, im from component spectra."""
    re, im = product_sums(F.col("re"), F.col("im"), F.col("br"), F.col("bi"), conjugate=True)
    root = F.sqrt(F.first("w"))
    out = spec.join(F.broadcast(mask), ["ku", "kv"]).join(_basis(basis), ["t", "comp"])
    return out.groupBy("slice_id", "coil", "t", "ku", "kv").agg((re * root).alias("re"), (im * root).alias("im"))


def collect_cells(samples: DataFrame, mask: DataFrame, basis: DataFrame) -> DataFrame:
    """The one pass over raw samples: per cell and component the sum over time of
    sqrt(w) times sample times basis, added up on the map side."""
    re, im = product_sums(F.col("re"), F.col("im"), F.col("br"), F.col("bi"))
    out = samples.join(F.broadcast(mask.select("t", "ku", "kv", F.sqrt("w").alias("root"))), ["t", "ku", "kv"])
    out = out.withColumns({"re": F.col("re") * F.col("root"), "im": F.col("im") * F.col("root")}).join(_basis(basis), "t")
    return out.groupBy("slice_id", "coil", "ku", "kv", "comp").agg(re.alias("re"), im.alias("im"))


def forward(img: DataFrame, n: int, mask: DataFrame, basis: DataFrame, coils: DataFrame | None = None) -> DataFrame:
    """Samples (times sqrt(w)) of a compressed image."""
    return sample(spectrum(coil_weighted(img, coils), n, ["slice_id", "coil", "comp"]), mask, basis)


def adjoint(samples: DataFrame, n: int, mask: DataFrame, basis: DataFrame, coils: DataFrame | None = None) -> DataFrame:
    """Compressed image of samples that carry sqrt(w) already."""
    return coil_combined(image(collect_cells(samples, mask, basis), n, ["slice_id", "coil", "comp"]), coils)


def weighted(samples: DataFrame, mask: DataFrame) -> DataFrame:
    """Raw samples times sqrt(w)."""
    out = samples.join(F.broadcast(mask.select("t", "ku", "kv", F.sqrt("w").alias("root"))), ["t", "ku", "kv"])
    return out.withColumns({"re": F.col("re") * F.col("root"), "im": F.col("im") * F.col("root")}).drop("root")


def normal_kernel(mask: DataFrame, basis: DataFrame) -> DataFrame:
    """ku, kv, comp, comp2, re, im: per cell the sum over its time points of
    w conj(B[t, comp]) B[t, comp2]. Shared by all slices of a sequence."""
    a = basis.select("t", "comp", F.col("re").alias("ar"), F.col("im").alias("ai"))
    re, im = product_sums(F.col("br"), F.col("bi"), F.col("ar"), F.col("ai"), conjugate=True)
    pairs = F.broadcast(a.join(_basis(basis, "comp2"), "t"))
    w = mask.join(pairs, "t").groupBy("ku", "kv", "comp", "comp2")
    return w.agg(
        F.sum(F.col("w") * (F.col("br") * F.col("ar") + F.col("bi") * F.col("ai"))).alias("re"),
        F.sum(F.col("w") * (F.col("bi") * F.col("ar") - F.col("br") * F.col("ai"))).alias("im"),
    )


def normal(img: DataFrame, n: int, kernel: DataFrame, coils: DataFrame | None = None) -> DataFrame:
    """Adjoint of forward, through the kernel: raw samples are not touched."""
    spec = spectrum(coil_weighted(img, coils), n, ["slice_id", "coil", "comp"])
    k = kernel.select("ku", "kv", "comp", "comp2", F.col("re").alias("kr"), F.col("im").alias("ki"))
    re, im = product_sums(F.col("re"), F.col("im"), F.col("kr"), F.col("ki"))
    mixed = spec.join(F.broadcast(k), ["ku", "kv", "comp"]).groupBy("slice_id", "coil", "ku", "kv", "comp2").agg(re.alias("re"), im.alias("im"))
    return coil_combined(image(mixed.withColumnRenamed("comp2", "comp"), n, ["slice_id", "coil", "comp"]), coils)


def coil_maps(samples: DataFrame, n: int, centre: int = 12) -> DataFrame:
    """coil, row, col, re, im from the centre of k-space averaged over time, each
    voxel divided by the root of the sum of squares over coils."""
    from pyspark.sql import Window

    far = lambda c: F.least(F.col(c), n - F.col(c))
    low = samples.filter((far("ku") <= centre // 2) & (far("kv") <= centre // 2))
    mean = low.groupBy("slice_id", "coil", "ku", "kv").agg(F.avg("re").alias("re"), F.avg("im").alias("im"))
    img = image(mean, n, ["slice_id", "coil"])
    total = F.sqrt(F.sum(F.col("re") ** 2 + F.col("im") ** 2).over(Window.partitionBy("slice_id", "row", "col")))
    safe = F.when(total > 0, total)
    return img.select("slice_id", "coil", "row", "col", (F.col("re") / safe).alias("re"), (F.col("im") / safe).alias("im"))


def noisy(samples: DataFrame, level: float = 0.001, channel: str = "each", seed: int = 0) -> DataFrame:
    """Gaussian noise with ``level`` of the slice's largest modulus as standard
    deviation, per real channel or of the complex value; keyed, so repeatable."""
    from ..functions.cx import normal_pair

    a, b = normal_pair(F.lit(seed), F.col("slice_id"), F.col("coil"), F.col("t"), F.col("ku"), F.col("kv"))
    top = samples.groupBy("slice_id").agg(F.max(F.hypot("re", "im")).alias("_top"))
    sigma = F.col("_top") * level / (math.sqrt(2) if channel == "complex" else 1.0)
    out = samples.join(F.broadcast(top), "slice_id")
    return out.withColumns({"re": F.col("re") + sigma * a, "im": F.col("im") + sigma * b}).drop("_top")


def ndft(img: DataFrame, points: DataFrame, n: int) -> DataFrame:
    """Exact transform at arbitrary positions (t, sample_no, kx, ky): the product
    of all voxels and all points, for small grids and as a yardstick."""
    angle = (F.col("row") * F.col("kx") + F.col("col") * F.col("ky")) * (-2 * math.pi / n)
    re, im = product_sums(F.col("re"), F.col("im"), F.cos(angle), F.sin(angle))
    out = img.crossJoin(F.broadcast(points)).groupBy("slice_id", "comp", "t", "sample_no")
    return out.agg((re / n).alias("re"), (im / n).alias("im"))


def _bessel(beta: float, distance, width: int):
    """Kaiser-Bessel window: the power series of I0 in nested form, as a column."""
    y = F.greatest(F.lit(0.0), 1 - (2 * distance / width) ** 2) * (beta * beta / 4)
    out = F.lit(1.0)
    for k in range(25, 0, -1):
        out = 1 + out * y / (k * k)
    return out


def _window_transform(x, beta: float, width: int, m: int):
    """Fourier transform of the window at image position x."""
    s = beta**2 - (math.pi * width * x / m) ** 2
    root = F.sqrt(F.abs(s))
    return F.lit(float(width)) * F.when(s > 1e-12, F.sinh(root) / root).when(s < -1e-12, F.sin(root) / root).otherwise(F.lit(1.0))


def degrid(img: DataFrame, points: DataFrame, n: int, width: int = 6, osf: int = 2) -> DataFrame:
    """Samples at arbitrary positions by an oversampled transform and a window of
    ``width`` cells: neighbours are exploded and joined by cell, not compared."""
    m = n * osf
    beta = math.pi * math.sqrt((width / osf) ** 2 * (osf - 0.5) ** 2 - 0.8)
    shade = _window_transform(F.col("row") - n / 2, beta, width, m) * _window_transform(F.col("col") - n / 2, beta, width, m)
    img = img.withColumns({"re": F.col("re") / shade, "im": F.col("im") / shade})
    spec = spectrum(img, m, ["slice_id", "comp"])
    near = F.sequence(F.lit(-(width // 2) + 1), F.lit(width // 2))
    p = points.withColumns({"u": F.col("kx") * osf, "v": F.col("ky") * osf})
    p = p.withColumn("du", F.explode(near)).withColumn("dv", F.explode(near))
    p = p.withColumns({"gu": F.floor("u") + F.col("du"), "gv": F.floor("v") + F.col("dv")})
    weight = _bessel(beta, F.abs(F.col("u") - F.col("gu")), width) * _bessel(beta, F.abs(F.col("v") - F.col("gv")), width)
    # the window is centred on the image, which shifts the phase of each cell
    turn = (F.col("gu") + F.col("gv") - F.col("u") - F.col("v")) * (math.pi / osf)
    p = p.select("t", "sample_no", F.pmod("gu", F.lit(m)).cast("int").alias("ku"), F.pmod("gv", F.lit(m)).cast("int").alias("kv"), (weight * F.cos(turn)).alias("pr"), (weight * F.sin(turn)).alias("pi"))
    re, im = product_sums(F.col("re"), F.col("im"), F.col("pr"), F.col("pi"))
    out = spec.join(p, ["ku", "kv"]).groupBy("slice_id", "comp", "t", "sample_no")
    return out.agg((re * m / n).alias("re"), (im * m / n).alias("im"))


def grid(samples: DataFrame, points: DataFrame, n: int, width: int = 6, osf: int = 2) -> DataFrame:
    """Adjoint of :func:`degrid`: samples spread to cells, summed, transformed."""
    m = n * osf
    beta = math.pi * math.sqrt((width / osf) ** 2 * (osf - 0.5) ** 2 - 0.8)
    near = F.sequence(F.lit(-(width // 2) + 1), F.lit(width // 2))
    p = points.withColumns({"u": F.col("kx") * osf, "v": F.col("ky") * osf})
    p = p.withColumn("du", F.explode(near)).withColumn("dv", F.explode(near))
    p = p.withColumns({"gu": F.floor("u") + F.col("du"), "gv": F.floor("v") + F.col("dv")})
    weight = _bessel(beta, F.abs(F.col("u") - F.col("gu")), width) * _bessel(beta, F.abs(F.col("v") - F.col("gv")), width)
    turn = (F.col("gu") + F.col("gv") - F.col("u") - F.col("v")) * (math.pi / osf)
    p = p.select("t", "sample_no", F.pmod("gu", F.lit(m)).cast("int").alias("ku"), F.pmod("gv", F.lit(m)).cast("int").alias("kv"), (weight * F.cos(turn)).alias("pr"), (weight * F.sin(turn)).alias("pi"))
    re, im = product_sums(F.col("re"), F.col("im"), F.col("pr"), F.col("pi"), conjugate=True)
    cells = samples.join(p, ["t", "sample_no"]).groupBy("slice_id", "comp", "ku", "kv").agg((re * m / n).alias("re"), (im * m / n).alias("im"))
    img = image(cells, m, ["slice_id", "comp"]).filter((F.col("row") < n) & (F.col("col") < n))
    shade = _window_transform(F.col("row") - n / 2, beta, width, m) * _window_transform(F.col("col") - n / 2, beta, width, m)
    return img.withColumns({"re": F.col("re") / shade, "im": F.col("im") / shade})
