"""Reconstruction from samples that lie off the grid, without rounding them.

Samples are spread onto a grid of twice the edge by a Kaiser-Bessel window, slice by
slice in one pass of sums; its transform, cropped and divided by the window's, is the
adjoint image. Iterations never return to the samples: the normal operator of a
sequence is a convolution, which is held as the transform of its response on a grid
of twice the edge. So the same algorithms run on it as on cells of the grid.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.scratch import cut
from .kernels import Encoder, Mask
from .setup import Setup, gain_weights, make, spiral_points

#: Oversampling of the grid, and width of the window in its cells.
OVER, WIDTH = 2, 6
BETA = math.pi * math.sqrt((WIDTH / OVER) ** 2 * (OVER - 0.5) ** 2 - 0.8)
#: Points up to which their table is broadcast.
POINT_ROWS = 1 << 18


def window(u: np.ndarray) -> np.ndarray:
    """The Kaiser-Bessel window at a distance of u cells."""
    return np.i0(BETA * np.sqrt(np.maximum(1 - (2 * u / WIDTH) ** 2, 0))) / WIDTH * (np.abs(u) <= WIDTH / 2)


def window_transform(x: np.ndarray, grid: int) -> np.ndarray:
    a = np.sqrt((BETA**2 - (math.pi * WIDTH * x / grid) ** 2).astype(complex))
    return (np.sinh(a) / a).real


def neighbours(g: np.ndarray, grid: int) -> tuple[np.ndarray, np.ndarray]:
    """Cells around each place g, and the window there: two points x WIDTH arrays."""
    first = np.ceil(g - WIDTH / 2).astype(np.int64)
    cell = first[:, None] + np.arange(WIDTH)
    return np.mod(cell, grid), window(cell - g[:, None])


def spread(values: np.ndarray, gx: np.ndarray, gy: np.ndarray, grid: int) -> np.ndarray:
    """Grid of the spread values, one per column of ``values``."""
    cx, wx = neighbours(gx, grid)
    cy, wy = neighbours(gy, grid)
    at = (cx[:, :, None] * grid + cy[:, None, :]).reshape(len(gx), -1)
    w = (wx[:, :, None] * wy[:, None, :]).reshape(len(gx), -1)
    out = np.zeros((grid * grid, values.shape[1]), complex)
    for j in range(values.shape[1]):
        v = values[:, j, None] * w
        out[:, j] = np.bincount(at.ravel(), v.real.ravel(), grid * grid) + 1j * np.bincount(at.ravel(), v.imag.ravel(), grid * grid)
    return out.reshape(grid, grid, -1)


def to_image(cells: np.ndarray, n: int) -> np.ndarray:
    """Image of n x n around the middle from spread values (grid, grid, columns)."""
    grid = len(cells)
    x = np.arange(-(n // 2), n - n // 2)
    image = np.fft.ifft2(cells, axes=(0, 1)) * grid**2
    shape = window_transform(x, grid)
    return image[np.ix_(x % grid, x % grid)] / (shape[:, None] * shape[None, :])[..., None]


def ndft(images: np.ndarray, kx: np.ndarray, ky: np.ndarray) -> np.ndarray:
    """Exact spectra (points x images) of images (count, n, n) at any frequency."""
    n = images.shape[1]
    x = np.arange(n) - n // 2
    ex, ey = np.exp(-2j * np.pi / n * kx[:, None] * x), np.exp(-2j * np.pi / n * ky[:, None] * x)
    return np.stack([((ex @ im) * ey).sum(axis=1) for im in images], axis=1) / n


@dataclass
class OffGridEncoder(Encoder):
    """The normal operator as a convolution: ``kernel`` is its response's transform,
    (2n, 2n, r, r)."""

    def __post_init__(self) -> None:
        pass

    def in_basis(self, basis: np.ndarray) -> Encoder:
        w = np.linalg.lstsq(self.basis, basis, rcond=None)[0]
        return replace(self, basis=basis, kernel=np.einsum("xyrk,ra,kb->xyab", self.kernel, w.conj(), w, optimize=True))

    def gather(self, s: np.ndarray) -> np.ndarray:
        x = np.stack([to_image(line, self.n) for line in s]) / self.n
        return x[0] if self.coils is None else (self.coils.conj()[..., None] * x).sum(axis=0)

    def normal(self, u: np.ndarray) -> np.ndarray:
        n = self.n
        x = u[None] if self.coils is None else self.coils[..., None] * u[None]
        s = np.fft.fft2(x, (2 * n, 2 * n), axes=(1, 2))
        v = np.fft.ifft2(np.einsum("qxyr,xyrk->qxyk", s, self.kernel), axes=(1, 2))[:, :n, :n] * self.scale
        return v[0] if self.coils is None else (self.coils.conj()[..., None] * v).sum(axis=0)

    def samples(self, u: np.ndarray) -> np.ndarray:
        raise NotImplementedError("off the grid the samples are not kept")


def response(n: int, basis: np.ndarray, t: np.ndarray, kx: np.ndarray, ky: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Transform of the normal operator's response, (2n, 2n, r, r)."""
    r = basis.shape[1]
    b, out = basis[t], np.zeros((2 * n, 2 * n, r, r), complex)
    upper = [(i, j) for i in range(r) for j in range(i, r)]
    for lo in range(0, len(upper), 16):
        part = upper[lo : lo + 16]
        values = np.stack([w * b[:, i].conj() * b[:, j] for i, j in part], axis=1)
        # displacements span 2n: as an image of that edge at doubled frequencies
        image = to_image(spread(values, 2 * OVER * kx, 2 * OVER * ky, 2 * OVER * n), 2 * n) / n**2
        image[0], image[:, 0] = 0, 0  # the displacement -n does not occur
        hat = np.fft.fft2(np.fft.ifftshift(image, axes=(0, 1)), axes=(0, 1))
        for c, (i, j) in enumerate(part):
            out[..., j, i] = hat[..., c].conj()  # the operator is its own adjoint
            out[..., i, j] = hat[..., c]
    return out


@dataclass
class OffGridSetup(Setup):
    """A setup whose ``mask`` holds t, kx, ky and weight of each point."""

    hat: np.ndarray | None = None

    @property
    def grid(self) -> int:
        return OVER * self.n

    def encoder(self, r: int) -> Encoder:
        t = self.mask[0]
        return OffGridEncoder(self.n, self.basis[:, :r], Mask(np.arange(len(t)), t, self.mask[3]), self.coils, self.hat[..., :r, :r], self.scale)


def make_offgrid(n: int, length: int, rank: int = 10, inner: float = 3.0, outer: float = 6.0, every: int = 1, coils: np.ndarray | None = None) -> OffGridSetup:
    """As :func:`make`, on the points of the spirals themselves."""
    s = make(n, length, rank, inner, outer, every=every, coils=coils)
    t, kx, ky = spiral_points(length, n, int(2 * n * n / (inner + outer)) + 8, inner, outer)
    cell = lambda v: np.mod(np.rint(v).astype(np.int64), n)
    w = gain_weights(t, cell(kx), cell(ky), n, s.basis[:, : min(10, s.basis.shape[1])])
    hat = response(n, s.basis, t, kx, ky, w)
    own = {f: getattr(s, f) for f in ("n", "length", "basis", "dictionary", "coils", "energy")}
    out = OffGridSetup(**own, mask=(t, kx, ky, w), scale=1.0, hat=hat)
    return replace(out, scale=1 / max(out.encoder(min(10, s.basis.shape[1])).spectral_radius(40), 1e-12))


def point_table(spark: SparkSession, s: OffGridSetup) -> DataFrame:
    """t, s (number in its readout), and where and how each point is spread."""
    t, kx, ky, w = s.mask
    (cx, wx), (cy, wy) = neighbours(OVER * kx, s.grid), neighbours(OVER * ky, s.grid)
    first = np.r_[True, t[1:] != t[:-1]]
    number = np.arange(len(t)) - np.maximum.accumulate(np.where(first, np.arange(len(t)), 0))
    df = pd.DataFrame({"t": t.astype(np.int32), "s": number.astype(np.int32), "kx": kx, "ky": ky, "w": w, "cx": cx.tolist(), "cy": cy.tolist(), "wx": wx.tolist(), "wy": wy.tolist()})
    out = spark.createDataFrame(df, "t int, s int, kx double, ky double, w double, cx array<int>, cy array<int>, wx array<double>, wy array<double>")
    return F.broadcast(out) if len(t) <= POINT_ROWS else cut(out, "points")


def phantom_points(spark: SparkSession, classes: np.ndarray, signals: np.ndarray, s: OffGridSetup) -> DataFrame:
    """slice_id 0's samples (coil, t, s, re, im) of ``classes`` (count, n, n) whose
    signals are the rows of ``signals``; coils are those of the setup."""
    coils = s.coils if s.coils is not None else np.ones((1, s.n, s.n))
    shared = spark.sparkContext.broadcast((classes, signals, coils))

    def run(batches):
        images, line, maps = shared.value
        for b in batches:
            t, kx, ky = b["t"].to_numpy(), b["kx"].to_numpy(), b["ky"].to_numpy()
            for q in range(len(maps)):
                v = (ndft(images * maps[q], kx, ky) * line[:, t].T).sum(axis=1)
                yield pd.DataFrame({"slice_id": np.int64(0), "coil": np.int32(q), "t": b["t"], "s": b["s"], "re": v.real, "im": v.imag})

    points = cut(point_table(spark, s).select("t", "s", "kx", "ky"), "places")
    return points.mapInPandas(run, "slice_id long, coil int, t int, s int, re double, im double")


def reduce_points(samples: DataFrame, s: OffGridSetup) -> DataFrame:
    """The state of each slice, as ``slices.reduce_samples`` makes it on cells: every
    sample is spread to WIDTH x WIDTH cells, which are added up before the shuffle."""
    spark = samples.sparkSession
    r = s.basis.shape[1]
    b = s.basis
    lines = pd.DataFrame({"t": np.arange(s.length, dtype=np.int32), **{f"b{j}": b[:, j].real for j in range(r)}, **{f"c{j}": b[:, j].imag for j in range(r)}})
    basis = spark.createDataFrame(lines).withColumn("t", F.col("t").cast("int"))
    x = samples.join(point_table(spark, s), ["t", "s"]).join(F.broadcast(basis), "t")
    x = x.select("*", F.posexplode(F.arrays_zip("cx", "wx")).alias("i", "px")).select("*", F.posexplode(F.arrays_zip("cy", "wy")).alias("j", "py"))
    share = F.col("w") * F.col("px.wx") * F.col("py.wy")
    power = F.when((F.col("i") == 0) & (F.col("j") == 0), F.col("w") * (F.col("re") ** 2 + F.col("im") ** 2)).otherwise(0.0)
    x = x.withColumns({"_r": F.col("re") * share, "_i": F.col("im") * share, "_p": power, "ku": F.col("px.cx"), "kv": F.col("py.cy")})
    sums = [F.sum("_p").alias("p")]
    for k in range(r):
        sums += [F.sum(F.col("_r") * F.col(f"b{k}") - F.col("_i") * F.col(f"c{k}")).alias(f"x{k}"), F.sum(F.col("_r") * F.col(f"c{k}") + F.col("_i") * F.col(f"b{k}")).alias(f"y{k}")]
    out = x.groupBy("slice_id", "coil", "ku", "kv").agg(*sums)
    cells = F.array(*[F.col(f"{a}{k}") for k in range(r) for a in ("x", "y")])
    return out.select("slice_id", F.lit(s.length).alias("length"), "coil", "ku", "kv", cells.alias("cells"), F.col("p").alias("power"))
