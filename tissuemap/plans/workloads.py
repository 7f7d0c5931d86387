"""The experiment workloads on generated phantoms, and on the given tables.

Each returns one row per configuration. ``size`` chooses the grid: thinned for
correctness runs, larger for the bench.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import VARIANTS, EngineConfig
from ..operators import encode, phantom
from ..sources import tables
from . import baselines, metrics
from .offgrid import make_offgrid, phantom_points, reduce_points
from .setup import make, simulate
from .slices import phantom_samples, reduce_samples, repeat_slices, run_slices

#: Spatial weights found by the sweep of w08 for samples scaled to a largest
#: adjoint value of one.
CLEAN, NOISY = 2e-3, 1e-2
NOISE = 0.001
#: Lengths of the sequence, a tenth of the published ones.
LENGTHS = (60, 80, 100, 150, 200, 300)
#: Rank of the projected-gradient baseline, and edge of the centre of k-space from
#: which coil maps are made, as published.
FULL_RANK, CENTRE = 200, 12


def scans(spark: SparkSession, sf_dir: str) -> int:
    """Number of scans of a workload over the given tables: one per hundred suppliers."""
    return -(-tables.read(spark, sf_dir, "supplier").count() // 100)


def flagship(spark: SparkSession, sf_dir: str, n: int = 16, length: int = 60) -> DataFrame:
    """Maps of ``par_bt`` with the class names of ``region``."""
    s = make(n, length, 10, 1.5, 3.0, every=10)
    ph = phantom.digital(spark, n)
    maps = run_slices(reduce_samples(phantom_samples(spark, ph, n, length, s.mask), [s]), [s], ["par_bt"], EngineConfig(lam=CLEAN, k_max=5))
    names = tables.read(spark, sf_dir, "region").select(F.col("r_regionkey").alias("class"), "r_name")
    where = ph.filter("mask").join(F.broadcast(names), "class").select("row", "col", F.col("r_name").alias("tissue"))
    return maps.join(F.broadcast(where), ["row", "col"]).select("slice_id", "row", "col", "tissue", "atom_id", "t1", "t2", F.round("rho", 6).alias("rho"))


def _state(spark: SparkSession, ph: DataFrame, n: int, lengths, noise: float, seeds: int, inner: float, outer: float, rank: int, coils: int = 0, bins: bool = False, weights: str = "gain", centre: int = 0):
    """Setups of all lengths and the reduced samples of ``seeds`` noisy scans."""
    factors = {b: phantom.field_factor(b) for b in range(1, 8)} if bins else None
    maps = None
    coil_df = None
    if coils:
        coil_df = phantom.coils(spark, n, coils)
        rows = coil_df.collect()  # coils x n x n values: of the sequence, not of the data
        maps = np.zeros((coils, n, n), complex)
        for r in rows:
            maps[r["coil"], r["row"], r["col"]] = r["re"] + 1j * r["im"]
    band = np.tile(np.floor(np.arange(n) * 7 / n).astype(int) + 1, (n, 1)) if bins else None
    setups = [make(n, v, rank, inner, outer, coils=maps, bins=band, factors=factors, weights=weights, centre=centre) for v in lengths]
    if bins:
        ph = ph.join(F.broadcast(phantom.field_bins(spark, n)), ["row", "col"])
    long = max(setups, key=lambda s: s.length)
    samples = repeat_slices(phantom_samples(spark, ph, n, long.length, long.mask, coil_df, factors=factors), seeds)
    if noise:
        samples = encode.noisy(samples, noise)
    return setups, reduce_samples(samples, setups)


def errors(spark: SparkSession, methods, n: int = 24, lengths=LENGTHS, noise: float = 0.0, seeds: int = 1, lam: float | None = None, lams=None, inner: float = 2.0, outer: float = 4.0, rank: int = 20, k_max: int = 10, **kind) -> DataFrame:
    """length, method, err_t1, err_t2 (mean over scans) on the digital phantom. Scans
    differ in their noise, so that a clean one is run once."""
    seeds = seeds if noise else 1
    ph = phantom.digital(spark, n)
    setups, state = _state(spark, ph, n, lengths, noise, seeds, inner, outer, rank, **kind)
    lam = lam if lam is not None else (NOISY if noise else CLEAN)
    maps = run_slices(state, setups, list(methods), EngineConfig(lam=lam, k_max=k_max), lams=lams)
    e = metrics.rel_error(maps, ph, ["length", "method", "slice_id"])
    return e.groupBy("length", "method").agg(F.avg("err_t1").alias("err_t1"), F.avg("err_t2").alias("err_t2"))


BEST_AND_BASELINES = ("par_bt", *baselines.MEASURED)


def variants_by_length(spark: SparkSession, noise: float = 0.0, **size) -> DataFrame:
    return errors(spark, VARIANTS, noise=noise, **size)


def best_against_baselines(spark: SparkSession, noise: float = 0.0, **size) -> DataFrame:
    return errors(spark, BEST_AND_BASELINES, noise=noise, **size)


def inserts_scan(spark: SparkSession, nation: DataFrame, n: int = 25, length: int = 100, long: int = 300, noise: float = NOISE, methods=BEST_AND_BASELINES, references=("base_zero_fill", "base_proj_grad")) -> DataFrame:
    """Per method and region of interest: spread of T1 and T2, ringing, and the
    difference to the maps of a long scan by each of ``references``."""
    ph = phantom.inserts(spark, nation, n)
    setups, state = _state(spark, ph.withColumn("mask", F.lit(True)), n, (length, long), noise, 1, 2.0, 4.0, 20)
    maps = run_slices(state, setups, list(methods), EngineConfig(lam=NOISY if noise else CLEAN))
    short = maps.filter(F.col("length") == length)
    ref = maps.filter((F.col("length") == long) & F.col("method").isin(*references)).withColumnRenamed("method", "reference")
    out = metrics.roi(short, ph, ["method"]).join(metrics.ringing(short, ph, ["method"]), ["method", "roi_id"])
    return out.join(metrics.vs_reference(short, ref, ["method", "reference"]), "method")


def multi_coil(spark: SparkSession, noise: float = NOISE, n: int = 24, lengths=(100, 300), methods=BEST_AND_BASELINES, centre: int = CENTRE, **size) -> DataFrame:
    """Five coils and seven field bands; the coil maps come from the scan itself."""
    return errors(spark, methods, n=n, lengths=lengths, noise=noise, rank=12, coils=5, bins=True, centre=centre, **size)


def weight_sweep(spark: SparkSession, noise: float, lams=(1e-5, 1e-4, 1e-3, 1e-2, 1e-1), methods=("seq_bt", "par_bt"), **size) -> DataFrame:
    return errors(spark, methods, noise=noise, lams=list(lams), **({"lengths": (60, 150)} | size))


def ablations(spark: SparkSession, **size) -> DataFrame:
    """Paired contrasts: contrast, length, gain_t1, gain_t2 (first over second)."""
    e = errors(spark, VARIANTS, **({"noise": NOISE} | size))
    pairs = [("step rule", "seq_fixed", "seq_bt"), ("matching", "seq_lazy", "seq_bt"), ("calibration, lazy", "seq_cal_lazy", "seq_lazy"), ("calibration, matched", "seq_cal_fixed", "seq_fixed"), ("splitting", "seq_bt", "par_bt")]
    t = spark.createDataFrame(pairs, "contrast string, first string, second string")
    a, b = e.withColumnsRenamed({"method": "first", "err_t1": "a1", "err_t2": "a2"}), e.withColumnsRenamed({"method": "second", "err_t1": "b1", "err_t2": "b2"})
    return t.join(a, "first").join(b, ["second", "length"]).select("contrast", "length", (F.col("a1") / F.col("b1")).alias("gain_t1"), (F.col("a2") / F.col("b2")).alias("gain_t2"))


def offgrid_errors(spark: SparkSession, methods=("par_bt", "seq_bt", "base_zero_fill", "base_proj_grad", "base_subspace"), n: int = 24, length: int = 100, noise: float = 0.0, seeds: int = 1, rank: int = 12) -> DataFrame:
    """method, err_t1, err_t2 of scans whose samples are not rounded to cells."""
    ph = phantom.digital(spark, n)
    kinds: dict[tuple[float, float], np.ndarray] = {}
    for r in ph.filter("pd > 0").collect():  # one image
        kinds.setdefault((r["t1"], r["t2"]), np.zeros((n, n)))[r["row"], r["col"]] = r["pd"]
    s = make_offgrid(n, length, rank, 2.0, 4.0)
    samples = phantom_points(spark, np.array(list(kinds.values())), simulate(*zip(*kinds, strict=True), length), s)
    samples = repeat_slices(samples, seeds if noise else 1)
    if noise:
        samples = encode.noisy(samples.withColumnsRenamed({"s": "ku"}).withColumn("kv", F.lit(0)), noise).withColumnRenamed("ku", "s").drop("kv")
    maps = run_slices(reduce_points(samples, s), [s], list(methods), EngineConfig(lam=NOISY if noise else CLEAN))
    e = metrics.rel_error(maps, ph, ["method", "slice_id"])
    return e.groupBy("method").agg(F.avg("err_t1").alias("err_t1"), F.avg("err_t2").alias("err_t2"))


def rank_errors(spark: SparkSession, ranks=(2, 4, 6, 8, 10, 15, 20), method: str = "seq_bt", n: int = 24, length: int = 100, noise: float = NOISE, seeds: int = 1) -> DataFrame:
    """rank, err_t1, err_t2: the error by the rank of the subspace."""
    ph = phantom.digital(spark, n)
    setups, state = _state(spark, ph, n, (length,), noise, seeds, 2.0, 4.0, max(ranks))
    maps = [run_slices(state, setups, [method], EngineConfig(lam=NOISY if noise else CLEAN, rank=r)).withColumn("rank", F.lit(r)) for r in ranks]
    e = metrics.rel_error(reduce(DataFrame.unionByName, maps), ph, ["rank", "slice_id"])
    return e.groupBy("rank").agg(F.avg("err_t1").alias("err_t1"), F.avg("err_t2").alias("err_t2"))


def cost(spark: SparkSession, n: int = 24, length: int = 60, methods=("par_bt", "seq_bt", "base_subspace"), slices: int = 1) -> DataFrame:
    """Per method: iterations, attempts, seconds per slice and per attempt, and
    the working set in megabytes."""
    s = make(n, length, 10, 2.0, 4.0)
    samples = repeat_slices(phantom_samples(spark, phantom.digital(spark, n), n, length, s.mask), slices)
    h = run_slices(reduce_samples(samples, [s]), [s], list(methods), EngineConfig(lam=CLEAN), history=True)
    per = h.groupBy("slice_id", "method").agg(F.max("iter").alias("last"), F.count("*").alias("attempts"), F.max("seconds").alias("seconds"))
    own = metrics.working_set(n, 10, length, len(s.mask[0]) // length, 48)
    return per.groupBy("method").agg(
        F.avg(F.col("last") + 1).alias("iterations"), F.avg("attempts").alias("attempts"), F.avg("seconds").alias("seconds"), F.avg(F.col("seconds") / F.col("attempts")).alias("seconds_per_attempt"),
        F.lit(own["own_mb"]).alias("own_mb"), F.lit(own["mixed_mb"]).alias("mixed_mb"),
    )


def sales_dealias(spark: SparkSession, sf_dir: str, width: int = 50, rank: int = 4, iters: int = 12, block: int = 8) -> DataFrame:
    """Missing part x month cells from low rank and smoothness over the grid.

    A tenth of the known cells, by digest, is held out. Grid rows are dealt in
    blocks, each a task of its own; per block the held-out error of the filled
    matrix is compared with that of the row mean.
    """
    m = tables.sales_matrix(spark, sf_dir, width).withColumn("v", F.log1p("v"))
    out = F.conv(F.substring(F.md5(F.concat_ws("-", "voxel", "t")), 1, 4), 16, 10).cast("int") % 10 == 0
    m = m.withColumn("held", out).withColumn("block", F.floor(F.col("row") / block).cast("int"))

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        from .kernels import nuclear_prox, tv_prox

        top, width_, months = int(pdf["row"].max()) - int(key[0]) * block + 1, int(pdf["col"].max()) + 1, int(pdf["t"].max()) + 1
        at = (pdf["row"].to_numpy() - int(key[0]) * block, pdf["col"].to_numpy(), pdf["t"].to_numpy())
        full, known = np.zeros((top, width_, months)), np.zeros((top, width_, months), bool)
        full[at], known[at] = pdf["v"], ~pdf["held"]
        mean = full[known].mean() if known.any() else 0.0
        u = np.full_like(full, mean)
        row_mean = np.where(known.sum(2) > 0, (full * known).sum(2) / np.maximum(known.sum(2), 1), mean)
        for _ in range(iters):
            g = np.where(known, full, u)
            x = nuclear_prox(g - mean, 0.15 * np.linalg.norm((g - mean).reshape(-1, months), 2)) + mean
            u = tv_prox(x, 0.05, 3)
        held = pdf["held"].to_numpy()
        truth = pdf["v"].to_numpy()[held]
        guess, plain = u[at][held], np.broadcast_to(row_mean[..., None], full.shape)[at][held]
        return pd.DataFrame({"block": [int(key[0])], "cells": [int(held.sum())], "err": [float(np.abs(guess - truth).sum())], "err_mean": [float(np.abs(plain - truth).sum())]})

    per = m.groupBy("block").applyInPandas(run, "block int, cells long, err double, err_mean double")
    return per.agg(F.sum("cells").alias("held_out"), (F.sum("err") / F.sum("cells")).alias("err"), (F.sum("err_mean") / F.sum("cells")).alias("err_row_mean"))
