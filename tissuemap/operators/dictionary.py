"""Parameter grid, signal simulation and the fingerprint dictionary."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.cx import v_norm
from .sequence import TE, TI

#: (first, last, step) in ms of the tissue parameter grid (fixed values).
T1_RANGES = ((10, 90, 10), (100, 1000, 20), (1040, 2000, 40), (2050, 4450, 100))
T2_RANGES = ((2, 8, 2), (10, 100, 5), (110, 300, 10), (350, 800, 50), (900, 1600, 100), (1800, 3000, 200))


def values(ranges) -> list[int]:
    return sorted({v for a, z, s in ranges for v in range(a, z + 1, s)})


def param_grid(spark: SparkSession, t1_ranges=T1_RANGES, t2_ranges=T2_RANGES) -> DataFrame:
    """atom_id, t1, t2 of all pairs with T1 >= T2, ids in order of (t1, t2)."""

    def axis(ranges, name: str) -> DataFrame:
        steps = F.array(*[F.sequence(F.lit(a), F.lit(z), F.lit(s)) for a, z, s in ranges])
        return spark.range(1).select(F.explode(F.array_distinct(F.flatten(steps)).cast("array<double>")).alias(name))

    pairs = axis(t1_ranges, "t1").crossJoin(F.broadcast(axis(t2_ranges, "t2"))).filter("t1 >= t2")
    # the grid is of fixed size (thousands of rows), so one ordered window is fine
    at = F.row_number().over(Window.orderBy("t1", "t2")) - 1
    return pairs.select(at.cast("int").alias("atom_id"), "t1", "t2")


def pairs_of(t1: DataFrame, t2: DataFrame) -> DataFrame:
    """t1, t2: all pairs of the distinct values of two axes with T1 >= T2. The second
    axis is of the size of a grid's and goes to all tasks."""
    return t1.distinct().crossJoin(F.broadcast(t2.distinct())).filter("t1 >= t2")


def simulate_fold(params: DataFrame, schedule: DataFrame, model: str = "coherent", b1: float = 1.0) -> DataFrame:
    """``params`` with ``sig`` array<double>: a fold over the schedule, no UDF.

    coherent: on-resonance rotation and relaxation of (x, m); spoiled: transverse
    magnetisation is lost between pulses, so T2 only scales the echo.
    """
    plan = schedule.groupBy().agg(F.sort_array(F.collect_list(F.struct("t", "tr_ms", (F.col("fa_deg") * b1).alias("fa_deg")))).alias("plan"))
    df = params.crossJoin(F.broadcast(plan))
    t1, t2 = F.col("t1"), F.col("t2")
    echo = F.exp(-TE / t2)
    start = F.struct(F.lit(0.0).alias("x"), (1 - 2 * F.exp(-TI / t1)).alias("m"), F.array().cast("array<double>").alias("out"))

    def step(s: Column, p: Column) -> Column:
        f, e1, e2 = F.radians(p["fa_deg"]), F.exp(-p["tr_ms"] / t1), F.exp(-p["tr_ms"] / t2)
        x = s["x"] * F.cos(f) + s["m"] * F.sin(f)
        m = s["m"] * F.cos(f) - s["x"] * F.sin(f)
        if model == "spoiled":
            x, m, keep = s["m"] * F.sin(f), s["m"] * F.cos(f), F.lit(0.0)
        else:
            keep = x * e2
        return F.struct(keep.alias("x"), (1 + (m - 1) * e1).alias("m"), F.concat(s["out"], F.array(x * echo)).alias("out"))

    return df.select(*params.columns, F.aggregate("plan", start, step, lambda s: s["out"]).alias("sig"))


def coherent_signals(t1: np.ndarray, t2: np.ndarray, tr: np.ndarray, fa: np.ndarray) -> np.ndarray:
    """The coherent model for many parameter pairs at once (rows)."""
    x, m = np.zeros_like(t1), 1 - 2 * np.exp(-TI / t1)
    out, echo = np.empty((len(t1), len(tr))), np.exp(-TE / t2)
    for i, (r, f) in enumerate(zip(tr, np.radians(fa), strict=True)):
        x, m = x * np.cos(f) + m * np.sin(f), m * np.cos(f) - x * np.sin(f)
        out[:, i] = x * echo
        x, m = x * np.exp(-r / t2), 1 + (m - 1) * np.exp(-r / t1)
    return out


def epg_signals(t1: np.ndarray, t2: np.ndarray, tr: np.ndarray, fa: np.ndarray, states: int = 20, b1: float = 1.0) -> np.ndarray:
    """Gradient-echo signals with dephasing states (extended phase graph).

    States of order k: F+ (dephasing), F- (rephasing), Z. Each pulse mixes all
    orders by the same 3x3 rotation; the gradient moves F by one order.
    """
    k = len(t1)
    plus, minus, z = (np.zeros((k, states), complex) for _ in range(3))
    z[:, 0] = 1 - 2 * np.exp(-TI / t1)
    out, echo = np.empty((k, len(tr)), complex), np.exp(-TE / t2)
    for i, (r, f) in enumerate(zip(tr, np.radians(fa * b1), strict=True)):
        c2, s2, s, c = np.cos(f / 2) ** 2, np.sin(f / 2) ** 2, np.sin(f), np.cos(f)
        plus, minus, z = (
            c2 * plus + s2 * minus - 1j * s * z,
            s2 * plus + c2 * minus + 1j * s * z,
            -0.5j * s * plus + 0.5j * s * minus + c * z,
        )
        out[:, i] = plus[:, 0] * echo
        e1, e2 = np.exp(-r / t1)[:, None], np.exp(-r / t2)[:, None]
        plus, minus, z = plus * e2, minus * e2, z * e1
        z[:, 0] += 1 - e1[:, 0]
        if states == 1:
            plus, minus = np.zeros_like(plus), np.zeros_like(minus)
            continue
        moved = np.empty_like(plus)
        moved[:, 1:] = plus[:, :-1]
        moved[:, 0] = np.conj(minus[:, 1])
        minus = np.concatenate([minus[:, 1:], np.zeros((k, 1), complex)], axis=1)
        minus[:, 0] = np.conj(moved[:, 0])
        plus = moved
    return out


def simulate_epg(params: DataFrame, schedule: DataFrame, states: int = 20, b1: float = 1.0) -> DataFrame:
    """As :func:`simulate_fold` with dephasing states and a complex signal; the
    schedule (thousands of rows at most) travels to the tasks."""
    rows = sorted(schedule.collect())
    tr, fa = np.array([r["tr_ms"] for r in rows]), np.array([r["fa_deg"] for r in rows])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            s = epg_signals(b["t1"].to_numpy(), b["t2"].to_numpy(), tr, fa, states, b1)
            yield b.assign(sig_re=list(s.real), sig_im=list(s.imag))

    shape = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in params.schema)
    return params.mapInPandas(run, f"{shape}, sig_re array<double>, sig_im array<double>")


def build(params: DataFrame, schedule: DataFrame, model: str = "coherent") -> DataFrame:
    """Atoms with their Euclidean norm."""
    if model == "epg":
        out = simulate_epg(params, schedule)
        square = F.zip_with("sig_re", "sig_im", lambda a, b: a * a + b * b)
        return out.withColumn("norm", F.sqrt(F.aggregate(square, F.lit(0.0), lambda s, x: s + x)))
    return simulate_fold(params, schedule, model).withColumn("norm", v_norm(F.col("sig")))
