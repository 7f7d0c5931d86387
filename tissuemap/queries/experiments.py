"""Queries of the experiment workloads, thinned; the bench runs them larger."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import VARIANTS, EngineConfig
from ..operators import phantom
from ..plans import baselines, workloads
from ..plans.setup import make
from ..plans.slices import phantom_samples, reduce_samples, run_slices
from ..sources import tables

SQL: dict[str, str] = {}


def _rounded(df: DataFrame, *names: str) -> DataFrame:
    return df.select(*[c for c in df.columns if c not in names], *[F.round(c, 6).alias(c) for c in names])


def w01_variants_clean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(workloads.variants_by_length(spark), "err_t1", "err_t2")


def w02_variants_noisy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(workloads.variants_by_length(spark, workloads.NOISE, seeds=workloads.scans(spark, sf_dir)), "err_t1", "err_t2")


def w03_baselines_clean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(workloads.best_against_baselines(spark), "err_t1", "err_t2")


def w04_baselines_noisy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(workloads.best_against_baselines(spark, workloads.NOISE, seeds=workloads.scans(spark, sf_dir)), "err_t1", "err_t2")


def w05_inserts(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = workloads.inserts_scan(spark, tables.read(spark, sf_dir, "nation"))
    return _rounded(out, "mean_t1", "mean_t2", "spread_t1", "spread_t2", "ringing", "diff_t1", "diff_t2")


def w05_inserts_clean(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = workloads.inserts_scan(spark, tables.read(spark, sf_dir, "nation"), noise=0.0)
    return _rounded(out, "mean_t1", "mean_t2", "spread_t1", "spread_t2", "ringing", "diff_t1", "diff_t2")


def w06_multi_coil(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(workloads.multi_coil(spark, seeds=workloads.scans(spark, sf_dir)), "err_t1", "err_t2")


def w06_multi_coil_clean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(workloads.multi_coil(spark, noise=0.0), "err_t1", "err_t2")


def w08_weight_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    clean = workloads.weight_sweep(spark, 0.0).withColumn("noise", F.lit(0.0))
    noisy = workloads.weight_sweep(spark, workloads.NOISE, seeds=workloads.scans(spark, sf_dir)).withColumn("noise", F.lit(workloads.NOISE))
    return _rounded(clean.unionByName(noisy), "err_t1", "err_t2")


def w09_ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paired contrasts, under both kinds of sample weights: with unit gains no step
    is rejected, so that the step rules differ under the other kind only."""
    size = {"lengths": (60, 100), "seeds": workloads.scans(spark, sf_dir)}
    gain = workloads.ablations(spark, **size).withColumn("weights", F.lit("gain"))
    count = workloads.ablations(spark, **size, weights="count", lam=workloads.CLEAN).withColumn("weights", F.lit("count"))
    return _rounded(gain.unionByName(count), "gain_t1", "gain_t2")


def w10_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.cost(spark)


def a16_offgrid_slices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reconstructions from samples off the grid, without and with noise."""
    clean = workloads.offgrid_errors(spark).withColumn("noise", F.lit(0.0))
    noisy = workloads.offgrid_errors(spark, noise=workloads.NOISE, seeds=workloads.scans(spark, sf_dir)).withColumn("noise", F.lit(workloads.NOISE))
    return _rounded(clean.unionByName(noisy), "err_t1", "err_t2")


def w07_rank_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error by the rank of the subspace."""
    return _rounded(workloads.rank_errors(spark, seeds=workloads.scans(spark, sf_dir)), "err_t1", "err_t2")


def b2_proj_grad_full_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The projected-gradient baseline at the rank it was published with."""
    e = workloads.errors(spark, ["base_proj_grad", "par_bt"], n=16, lengths=(200,), noise=workloads.NOISE, seeds=workloads.scans(spark, sf_dir), rank=workloads.FULL_RANK)
    return _rounded(e, "err_t1", "err_t2")


def w11_sales_dealias(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(workloads.sales_dealias(spark, sf_dir), "err", "err_row_mean")


def w15_subspace_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(workloads.errors(spark, ["base_subspace", "base_subspace_10"], noise=workloads.NOISE, seeds=workloads.scans(spark, sf_dir)), "err_t1", "err_t2")


def _phantom_run(spark: SparkSession, methods, cfg: EngineConfig, history: bool = False) -> DataFrame:
    s = make(16, 60, 12, 1.5, 3.0, every=5)
    state = reduce_samples(phantom_samples(spark, phantom.digital(spark, 16), 16, 60, s.mask), [s])
    return run_slices(state, [s], list(methods), cfg, history)


def _summary(maps: DataFrame) -> DataFrame:
    out = maps.groupBy("method").agg(F.count("*").alias("voxels"), F.avg("t1").alias("t1"), F.avg("t2").alias("t2"), F.avg((F.col("rho") == 0).cast("double")).alias("dark"))
    return _rounded(out, "t1", "t2", "dark")


def a25_autocal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Calibration from one projected step and from the raw adjoint."""
    return _summary(_phantom_run(spark, ["seq_cal_lazy", "seq_cal_lazy_raw"], EngineConfig(lam=1e-3)))


def a56_lipschitz(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spectral radius of the normal operator after scaling, by rank."""
    s = make(16, 60, 12, 1.5, 3.0, every=25)
    return spark.createDataFrame([(r, round(s.encoder(r).spectral_radius(40), 6)) for r in (4, 8, 10, 12)], "rank int, radius double")


def a62_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _summary(_phantom_run(spark, VARIANTS, EngineConfig(lam=1e-3, k_max=5)))


def a64_convex_mode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Matching dropped: proximal gradient; fidelity by iteration."""
    h = _phantom_run(spark, ["convex"], EngineConfig(lam=1e-4, k_max=8), history=True)
    return _rounded(h.filter("accepted").select("iter", "fidelity", "residual"), "fidelity", "residual")


def a65_history(spark: SparkSession, sf_dir: str) -> DataFrame:
    h = _phantom_run(spark, ["seq_bt", "par_bt", "seq_bt_safe", "par_bt_safe"], EngineConfig(lam=1e-3, k_max=6), history=True)
    return _rounded(h.select("method", "iter", "attempt", "step", "fidelity", "residual", "accepted", "outcome"), "step", "fidelity", "residual")


def b4_subspace(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _summary(_phantom_run(spark, baselines.MEASURED, EngineConfig()))


def b5_described_baselines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _summary(_phantom_run(spark, baselines.DESCRIBED, EngineConfig(lam=1e-3, k_max=5)))


QUERIES = {
    f.__name__: f
    for f in (
        w01_variants_clean, w02_variants_noisy, w03_baselines_clean, w04_baselines_noisy, w05_inserts, w05_inserts_clean, w06_multi_coil, w06_multi_coil_clean, w08_weight_sweep,
        w09_ablations, w07_rank_error, a16_offgrid_slices, b2_proj_grad_full_rank, w10_cost, w11_sales_dealias, w15_subspace_rank, a25_autocal_data, a56_lipschitz, a62_variants, a64_convex_mode, a65_history, b4_subspace, b5_described_baselines,
    )
}
