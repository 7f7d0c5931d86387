"""From raw samples to maps: one pass over the samples, then a task per slice.

The pass adds up, per frequency cell and component, the samples of a slice in the
temporal basis; its output does not depend on the length of the scan. Whatever
iterates afterwards runs on that state inside one task, and slices are spread over
the cluster. Scans of several lengths are prefixes of one table of samples.
"""

from __future__ import annotations

import time
from dataclasses import replace
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import STUDIES, VARIANTS, EngineConfig
from ..sources.scratch import cut
from . import baselines
from .kernels import calibration, estimate_coils, project, project_bins, reconstruct
from .setup import Setup, simulate

#: Rows of masks that are broadcast; longer ones (time points x samples x lengths)
#: are written once and joined on their key.
MASK_ROWS = 1 << 20
MAPS = "slice_id long, length int, method string, row int, col int, atom_id int, t1 double, t2 double, rho double"
HISTORY = "slice_id long, length int, method string, iter int, attempt int, step double, fidelity double, residual double, accepted boolean, outcome string, seconds double"


def phantom_samples(spark: SparkSession, phantom: DataFrame, n: int, length: int, mask: tuple, coils: DataFrame | None = None, model: str = "coherent", factors: dict[int, float] | None = None) -> DataFrame:
    """slice_id 0's samples: coil, t, ku, kv, re, im of a phantom of classes.

    Voxels of equal tissue (and field bin) share a signal, so each class is
    transformed once, and samples are sums over the classes at the sampled cells.
    """
    from ..operators.encode import spectrum, spectrum_packed

    p = phantom.filter("pd > 0")
    if "b1_bin" not in p.columns:
        p = p.withColumn("b1_bin", F.lit(0))
    kinds = p.select("t1", "t2", "b1_bin").distinct().orderBy("t1", "t2", "b1_bin").collect()  # tissue classes: tens
    rows = []
    for k, kind in enumerate(kinds):
        s = simulate([kind["t1"]], [kind["t2"]], length, model, (factors or {}).get(kind["b1_bin"], 1.0))[0]
        rows += [(k, t, float(v.real), float(v.imag)) for t, v in enumerate(s)]
    signal = spark.createDataFrame(pd.DataFrame(rows, columns=["kind", "t", "sr", "si"])).withColumn("kind", F.col("kind").cast("int")).withColumn("t", F.col("t").cast("int"))
    names = spark.createDataFrame([(float(x["t1"]), float(x["t2"]), x["b1_bin"], k) for k, x in enumerate(kinds)], "t1 double, t2 double, b1_bin int, kind int")
    img = p.join(F.broadcast(names), ["t1", "t2", "b1_bin"]).select("kind", "row", "col", F.col("pd").alias("re"), F.lit(0.0).alias("im"))
    keys = ["kind"]
    if coils is None:
        img = img.withColumn("coil", F.lit(0))
    else:
        c = coils.select("coil", "row", "col", F.col("re").alias("cr"), F.col("im").alias("ci"))
        img = img.join(F.broadcast(c), ["row", "col"]).select("kind", "coil", "row", "col", (F.col("re") * F.col("cr")).alias("re"), (F.col("re") * F.col("ci")).alias("im"))
    spec = (spectrum if n <= 32 else spectrum_packed)(img, n, [*keys, "coil"])
    cells = mask_table(spark, mask).select("t", "ku", "kv")
    out = cells.join(spec, ["ku", "kv"]).join(F.broadcast(signal), ["kind", "t"]).groupBy("coil", "t", "ku", "kv")
    out = out.agg(F.sum(F.col("re") * F.col("sr") - F.col("im") * F.col("si")).alias("re"), F.sum(F.col("re") * F.col("si") + F.col("im") * F.col("sr")).alias("im"))
    return out.select(F.lit(0).cast("long").alias("slice_id"), "coil", "t", "ku", "kv", "re", "im")


def mask_table(spark: SparkSession, mask: tuple) -> DataFrame:
    t, ku, kv, w = mask
    df = pd.DataFrame({"t": np.asarray(t, np.int32), "ku": np.asarray(ku, np.int32), "kv": np.asarray(kv, np.int32), "w": np.asarray(w, float)})
    return spark.createDataFrame(df, "t int, ku int, kv int, w double")


def repeat_slices(samples: DataFrame, count: int) -> DataFrame:
    """The same object scanned ``count`` times. One scan is small and may come in one
    part, its repetitions are not: cells are dealt to all cores first."""
    spark = samples.sparkSession
    ids = spark.range(count).select(F.col("id").alias("_s"))
    if count > 1:
        samples = samples.repartition(spark.sparkContext.defaultParallelism, *[c for c in ("ku", "kv", "s") if c in samples.columns])
    return samples.crossJoin(F.broadcast(ids)).withColumn("slice_id", F.col("_s")).drop("_s")


def reduce_samples(samples: DataFrame, setups: list[Setup]) -> DataFrame:
    """slice_id, length, coil, ku, kv, cells (2R doubles), power: the state that
    replaces the raw samples, for every length at once.

    Sums are scalar columns, so aggregation buffers have fixed width; equal cells
    of a task are added up before the shuffle.
    """
    spark = samples.sparkSession
    r = max(s.basis.shape[1] for s in setups)
    masks = reduce(DataFrame.unionByName, [mask_table(spark, s.mask).withColumn("length", F.lit(s.length)) for s in setups])
    masks = F.broadcast(masks) if sum(len(s.mask[0]) for s in setups) <= MASK_ROWS else cut(masks, "masks")
    lines = []
    for s in setups:
        b = np.zeros((s.length, r), complex)
        b[:, : s.basis.shape[1]] = s.basis
        lines.append(pd.DataFrame({"length": np.int32(s.length), "t": np.arange(s.length, dtype=np.int32), **{f"b{j}": b[:, j].real for j in range(r)}, **{f"c{j}": b[:, j].imag for j in range(r)}}))
    basis = spark.createDataFrame(pd.concat(lines)).withColumn("length", F.col("length").cast("int")).withColumn("t", F.col("t").cast("int"))
    real = all(not np.iscomplexobj(s.basis) for s in setups)
    x = samples.join(masks, ["t", "ku", "kv"]).join(F.broadcast(basis), ["length", "t"])
    root = F.sqrt("w")
    x = x.withColumns({"_r": F.col("re") * F.col("w"), "_i": F.col("im") * F.col("w"), "_p": root * root * (F.col("re") ** 2 + F.col("im") ** 2)})
    sums = [F.sum("_p").alias("p")]
    for j in range(r):
        b, c = F.col(f"b{j}"), F.col(f"c{j}")
        sums += [F.sum(F.col("_r") * b if real else F.col("_r") * b - F.col("_i") * c).alias(f"x{j}"), F.sum(F.col("_i") * b if real else F.col("_r") * c + F.col("_i") * b).alias(f"y{j}")]
    out = x.groupBy("slice_id", "length", "coil", "ku", "kv").agg(*sums)
    cells = F.array(*[F.col(f"{a}{j}") for j in range(r) for a in ("x", "y")])
    return out.select("slice_id", "length", "coil", "ku", "kv", cells.alias("cells"), F.col("p").alias("power"))


def run_method(name: str, cells: np.ndarray, power: float, s: Setup, base: EngineConfig):
    """One method on one slice: atom, rho, T1 and T2 maps, and history."""
    known = {**VARIANTS, **STUDIES}
    cfg = known[name].but(lam=base.lam, k_max=base.k_max, rank=base.rank, tv_iters=base.tv_iters, spatial=base.spatial) if name in known else base
    full = cells.shape[-1]
    r = min({"base_proj_grad": full, "base_proj_grad_ratio": full, "base_proj_lp": full, "base_subspace": 8}.get(name, cfg.rank), full)
    if name == "base_subspace_10":
        r = min(10, full)
    enc = s.encoder(full if cfg.calibrated else r)
    d = s.atoms(full if cfg.calibrated else r)
    part = cells[..., : full if cfg.calibrated else r] * s.scale
    b = enc.gather(part)
    top = float(np.abs(b).max()) or 1.0
    b, power = b / top, power * s.scale / top**2
    match = None
    if s.by_bin and not cfg.calibrated:
        by_bin = s.bin_atoms(r)
        match = lambda z: project_bins(z, by_bin, s.bins, cfg.score)
    if cfg.calibrated:
        w = calibration(b, d, cfg)
        enc, d, b = enc.in_basis(enc.basis @ w), d.rotated(w), b @ w
        if s.by_bin:
            by_bin = {k: x.rotated(w) for k, x in s.bin_atoms(full).items()}
            match = lambda z: project_bins(z, by_bin, s.bins, cfg.score)
    match = match or (lambda z: project(z, d, cfg.score))
    if name in known:
        out = reconstruct(b, power, enc, d, cfg, match)
        return out.atom, out.rho * top, s.dictionary.t1[out.atom], s.dictionary.t2[out.atom], out.history
    atom, rho, history = baselines.run(name, part / top, b, power, enc, d, cfg, match)
    return atom, rho * top, s.dictionary.t1[atom], s.dictionary.t2[atom], history


def run_slices(state: DataFrame, setups: list[Setup], methods: list[str], base: EngineConfig | None = None, history: bool = False, lams: list[float] | None = None) -> DataFrame:
    """Maps (or histories) of every slice, length and method; a task per slice and
    length runs the methods one after the other.

    Where there are fewer slices than cores the methods are dealt to several tasks,
    each of which gets the slice's state. With ``lams`` each method runs once per
    weight, named method@weight.
    """
    base = base or EngineConfig()
    spark = state.sparkSession
    shared = spark.sparkContext.broadcast({s.length: s for s in setups})
    names = [(m, m, base.lam) for m in methods] if lams is None else [(f"{m}@{v:g}", m, v) for m in methods for v in lams]
    state = cut(state, "state")
    slices = state.select("slice_id", "length").distinct().count()
    parts = max(1, min(len(names), spark.sparkContext.defaultParallelism // max(1, slices)))

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        slice_id, length, part = key
        s = shared.value[int(length)]
        q = int(pdf["coil"].max()) + 1
        flat = np.array(pdf["cells"].tolist(), float)
        cells = np.zeros((q, s.grid, s.grid, s.basis.shape[1]), complex)
        cells[pdf["coil"], pdf["ku"], pdf["kv"]] = (flat[:, 0::2] + 1j * flat[:, 1::2])[:, : s.basis.shape[1]]
        if s.centre:
            s = replace(s, coils=estimate_coils(cells, s.centre))
        power = float(pdf["power"].sum())
        return pd.concat([one(int(slice_id), int(length), *name, cells, power, s) for name in names[int(part) :: parts]])

    def one(slice_id: int, length: int, label: str, method: str, lam: float, cells: np.ndarray, power: float, s: Setup) -> pd.DataFrame:
        began = time.time()
        atom, rho, t1, t2, steps = run_method(method, cells, power, s, base.but(lam=lam))
        head = {"slice_id": slice_id, "length": np.int32(length), "method": label}
        if history:
            out = pd.DataFrame(steps or [{"iter": 0, "attempt": 0, "step": 1.0, "fidelity": float("nan"), "residual": float("nan"), "accepted": True, "outcome": "accepted"}])
            return out.assign(**head, seconds=time.time() - began)[[c.split()[0] for c in HISTORY.split(", ")]]
        row, col = np.divmod(np.arange(s.n**2), s.n)
        return pd.DataFrame({**head, "row": row.astype(np.int32), "col": col.astype(np.int32), "atom_id": atom.ravel().astype(np.int32), "t1": t1.ravel(), "t2": t2.ravel(), "rho": rho.ravel()})

    dealt = state.withColumn("part", F.explode(F.array(*[F.lit(k) for k in range(parts)])))
    # states are small for the work on them, so their number decides and not their bytes
    spread = max(1, min(slices * parts, 4 * spark.sparkContext.defaultParallelism))
    return dealt.repartition(spread, "slice_id", "length", "part").groupBy("slice_id", "length", "part").applyInPandas(run, HISTORY if history else MAPS)
