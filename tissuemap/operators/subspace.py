"""Low-rank bases of temporal signals."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def gram(df: DataFrame, key: str = "voxel", index: str = "t", value: str = "v") -> DataFrame:
    """t, t2, g: sums of products of columns, upper triangle and its mirror.

    Rows are packed first, so pairs are made within a row and added on the map
    side; what is shuffled is the L x L result.
    """
    rows = df.groupBy(key).agg(F.collect_list(F.struct(F.col(index).alias("t"), F.col(value).alias("v"))).alias("p"))
    a = rows.select(F.col("p"), F.explode("p").alias("a")).select("a", F.explode("p").alias("b")).filter("a.t <= b.t")
    half = a.groupBy(F.col("a.t").alias("t"), F.col("b.t").alias("t2")).agg(F.sum(F.col("a.v") * F.col("b.v")).alias("g"))
    return half.unionByName(half.filter("t < t2").select(F.col("t2").alias("t"), F.col("t").alias("t2"), "g"))


def gram_packed(df: DataFrame, col: str = "sig") -> np.ndarray:
    """L x L Gram matrix of packed real rows: one matrix per task, summed."""
    import pyarrow as pa

    def run(batches):
        total = None
        for b in batches:
            x = np.array(b.column(0).to_pylist(), float)
            if len(x):
                total = x.T @ x if total is None else total + x.T @ x
        if total is not None:
            yield pa.record_batch([pa.array(range(len(total)), pa.int32()), pa.array(total.tolist(), pa.list_(pa.float64()))], ["t", "g"])

    part = df.select(col).mapInArrow(run, "t int, g array<double>")
    rows = part.select("t", F.posexplode("g").alias("t2", "g")).groupBy("t", "t2").agg(F.sum("g").alias("g")).collect()
    size = 1 + max((r["t"] for r in rows), default=-1)
    out = np.zeros((size, size))
    for r in rows:
        out[r["t"], r["t2"]] = r["g"]
    return out


def gram_matrix(g: DataFrame) -> tuple[np.ndarray, list[int]]:
    """The Gram table as a matrix; L x L values, so bounded by the sequence."""
    rows = g.collect()
    names = sorted({r["t"] for r in rows})
    at = {t: i for i, t in enumerate(names)}
    out = np.zeros((len(names), len(names)))
    for r in rows:
        out[at[r["t"]], at[r["t2"]]] = r["g"]
    return out, names


def leading(g: np.ndarray, r: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Eigenvalues (falling) and vectors of a Hermitian matrix; the entry of
    largest modulus in each vector is made positive."""
    val, vec = np.linalg.eigh(g)
    val, vec = np.maximum(val[::-1], 0), vec[:, ::-1]
    top = vec[np.abs(vec).argmax(axis=0), np.arange(vec.shape[1])]
    vec = vec * (np.conj(top) / np.abs(top))
    return val[:r], vec[:, :r]


def dict_basis(dictionary: DataFrame, r: int = 10) -> np.ndarray:
    """L x r: first right singular vectors of the dictionary."""
    return leading(gram_packed(dictionary), r)[1]


def basis_table(spark, basis: np.ndarray, times: list[int] | None = None) -> DataFrame:
    times = times or list(range(len(basis)))
    rows = [(int(t), j, float(np.real(v)), float(np.imag(v))) for t, line in zip(times, basis, strict=True) for j, v in enumerate(line)]
    return spark.createDataFrame(rows, "t int, comp int, re double, im double")


def compress(df: DataFrame, basis: DataFrame, keys: list[str]) -> DataFrame:
    """Real rows (keys, t, v) in the basis: keys, comp, v. One shuffle, of sums."""
    b = basis.select("t", "comp", F.col("re").alias("b"))
    return df.join(F.broadcast(b), "t").groupBy(*keys, "comp").agg(F.sum(F.col("v") * F.col("b")).alias("v"))


def decompress(df: DataFrame, basis: DataFrame, keys: list[str]) -> DataFrame:
    b = basis.select("t", "comp", F.col("re").alias("b"))
    return df.join(F.broadcast(b), "comp").groupBy(*keys, "t").agg(F.sum(F.col("v") * F.col("b")).alias("v"))


def autocal(calibration: DataFrame, basis: DataFrame, r: int, keys: list[str]) -> np.ndarray:
    """R x r rotation: right singular vectors of calibration rows in the basis."""
    c = compress(calibration, basis, keys)
    g, _ = gram_matrix(gram(c.withColumn("_key", F.concat_ws("-", *keys)), "_key", "comp", "v"))
    return leading(g, r)[1]


def _spectral(df: DataFrame, keys: list[str], weight) -> DataFrame:
    """X -> X V f(sigma) V^T, by the Gram's eigenvectors."""
    g, times = gram_matrix(gram(df.withColumn("_key", F.concat_ws("-", *keys)), "_key"))
    val, vec = leading(g)
    mixing = (vec * weight(np.sqrt(val))) @ vec.T
    rows = [(t, t2, float(mixing[i, j])) for i, t in enumerate(times) for j, t2 in enumerate(times)]
    m = df.sparkSession.createDataFrame(rows, "t int, t2 int, m double")
    return df.join(F.broadcast(m), "t").groupBy(*keys, F.col("t2").alias("t")).agg(F.sum(F.col("v") * F.col("m")).alias("v"))


def rank_project(df: DataFrame, r: int, keys: list[str]) -> DataFrame:
    """Nearest matrix of rank r (hard threshold of singular values)."""
    return _spectral(df, keys, lambda s: (np.arange(len(s)) < r).astype(float))


def nuclear_prox(df: DataFrame, tau: float, keys: list[str]) -> DataFrame:
    """Soft threshold of singular values."""
    return _spectral(df, keys, lambda s: np.where(s > tau, (s - tau) / np.where(s > 0, s, 1), 0.0))


def rank_energy(values: DataFrame) -> DataFrame:
    """comp, energy, share: retained energy by rank from (comp, value)."""
    w = Window.orderBy("comp")
    whole = F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return values.select("comp", F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("energy"), (F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)) / whole).alias("share"))


def power_values(g: DataFrame, iters: int = 3) -> DataFrame:
    """iter, value: Rayleigh quotients of power iteration from a constant vector,
    as joins and sums only (L x L values; the plan is unrolled)."""
    x = g.select("t").distinct().withColumn("x", F.lit(1.0))
    out = None
    for i in range(iters):
        y = g.join(F.broadcast(x.withColumnRenamed("t", "t2")), "t2").groupBy("t").agg(F.sum(F.col("g") * F.col("x")).alias("y"))
        both = y.join(F.broadcast(x), "t")
        q = both.agg(F.lit(i).alias("iter"), (F.sum(F.col("x") * F.col("y")) / F.sum(F.col("x") ** 2)).alias("value"))
        out = q if out is None else out.unionByName(q)
        norm = y.agg(F.sqrt(F.sum(F.col("y") ** 2)).alias("n"))
        x = y.crossJoin(F.broadcast(norm)).select("t", (F.col("y") / F.col("n")).alias("x"))
    return out


def power_basis(g: np.ndarray, r: int, iters: int = 200) -> np.ndarray:
    """Leading vectors by power iteration with deflation."""
    g, out = g.copy(), []
    for _ in range(r):
        x = np.ones(len(g)) + np.arange(len(g)) * 1e-3
        for _ in range(iters):
            y = g @ x
            n = np.linalg.norm(y)
            if n == 0:
                break
            x = y / n
        out.append(x)
        g -= (x @ g @ x) * np.outer(x, x)
    return np.column_stack(out)
