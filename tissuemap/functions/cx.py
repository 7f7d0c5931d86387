"""Complex numbers as struct<re, im>, and flat pairs of sums for hot loops.

Everything here is a Catalyst expression. The inner product conjugates its
second argument, everywhere.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def cx(re, im=0.0) -> Column:
    lift = lambda v: v if isinstance(v, Column) else F.lit(float(v))
    return F.struct(lift(re).cast("double").alias("re"), lift(im).cast("double").alias("im"))


def add(a: Column, b: Column) -> Column:
    return cx(a["re"] + b["re"], a["im"] + b["im"])


def sub(a: Column, b: Column) -> Column:
    return cx(a["re"] - b["re"], a["im"] - b["im"])


def mul(a: Column, b: Column) -> Column:
    return cx(a["re"] * b["re"] - a["im"] * b["im"], a["re"] * b["im"] + a["im"] * b["re"])


def conj(a: Column) -> Column:
    return cx(a["re"], -a["im"])


def scale(a: Column, s) -> Column:
    return cx(a["re"] * s, a["im"] * s)


def abs2(a: Column) -> Column:
    return a["re"] * a["re"] + a["im"] * a["im"]


def modulus(a: Column) -> Column:
    return F.sqrt(abs2(a))


def arg(a: Column) -> Column:
    return F.atan2(a["im"], a["re"])


def expi(angle: Column) -> Column:
    return cx(F.cos(angle), F.sin(angle))


def dot(a: Column, b: Column) -> Column:
    """Sum of a_i times the conjugate of b_i over two arrays of complex numbers."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: mul(x, conj(y))), cx(0.0), add)


def product_sums(ar, ai, br, bi, conjugate: bool = False) -> tuple[Column, Column]:
    """Two scalar sums for the sum over a group of a*b, or a*conj(b): fixed-width
    aggregation buffers keep this in generated code."""
    s = -1 if conjugate else 1
    return F.sum(ar * br - s * ai * bi), F.sum(s * ar * bi + ai * br)


def v_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def v_norm(a: Column) -> Column:
    return F.sqrt(v_dot(a, a))


def v_scale(a: Column, s: Column) -> Column:
    return F.transform(a, lambda x: x * s)


def v_axpy(s: Column, a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: s * x + y)


def v_normalise(a: Column) -> Column:
    return v_scale(a, 1.0 / v_norm(a))


def uniform(*key: Column) -> Column:
    """A number in (0, 1) from a digest of the key: the same in any partitioning
    and in any engine that has md5."""
    text = F.concat_ws("-", *[k.cast("string") for k in key])
    return (F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long").cast("double") + 0.5) / F.lit(float(2**52))


def normal_pair(*key: Column) -> tuple[Column, Column]:
    """Two independent standard normal numbers from a key (Box-Muller)."""
    u, v = uniform(*key, F.lit("u")), uniform(*key, F.lit("v"))
    radius = F.sqrt(-2.0 * F.log(u))
    return radius * F.cos(2 * F.pi() * v), radius * F.sin(2 * F.pi() * v)
