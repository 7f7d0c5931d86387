"""Accuracy and cost measures over tables of maps."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def rel_error(maps: DataFrame, truth: DataFrame, keys: list[str]) -> DataFrame:
    """keys, err_t1, err_t2: mean relative error over masked voxels."""
    t = F.broadcast(truth.filter("mask").select("row", "col", F.col("t1").alias("true1"), F.col("t2").alias("true2")))
    err = lambda a, b: F.avg(F.abs(F.col(a) - F.col(b)) / F.col(b))
    return maps.join(t, ["row", "col"]).groupBy(*keys).agg(err("t1", "true1").alias("err_t1"), err("t2", "true2").alias("err_t2"))


def roi(maps: DataFrame, rois: DataFrame, keys: list[str]) -> DataFrame:
    """keys, roi_id: mean and spread (std over mean) of T1 and T2 per region."""
    r = F.broadcast(rois.filter("roi_id is not null").select("row", "col", "roi_id", "n_nationkey"))
    per = maps.join(r, ["row", "col"]).groupBy(*keys, "roi_id", "n_nationkey")
    disc = per.agg(*[f(c).alias(f"{n}_{c}") for c in ("t1", "t2") for f, n in ((F.avg, "mean"), (F.stddev_pop, "std"))])
    spread = [F.avg(F.col(f"std_{c}") / F.col(f"mean_{c}")).alias(f"spread_{c}") for c in ("t1", "t2")]
    return disc.groupBy(*keys, "roi_id").agg(F.avg("mean_t1").alias("mean_t1"), F.avg("mean_t2").alias("mean_t2"), *spread)


def vs_reference(maps: DataFrame, reference: DataFrame, keys: list[str]) -> DataFrame:
    """Mean relative difference to a long scan's maps, which are not the truth; keys
    that the maps lack are the reference's."""
    own = [k for k in keys if k not in maps.columns]
    r = reference.select("row", "col", *own, F.col("t1").alias("ref1"), F.col("t2").alias("ref2"))
    return maps.join(r, ["row", "col"]).groupBy(*keys).agg(
        F.avg(F.abs(F.col("t1") - F.col("ref1")) / F.col("ref1")).alias("diff_t1"), F.avg(F.abs(F.col("t2") - F.col("ref2")) / F.col("ref2")).alias("diff_t2")
    )


def pd_ratio(maps: DataFrame, truth: DataFrame, keys: list[str]) -> DataFrame:
    """keys, pd_ratio: mean of estimated over true density within the mask."""
    t = F.broadcast(truth.filter("mask").select("row", "col", "pd"))
    return maps.join(t, ["row", "col"]).groupBy(*keys).agg(F.avg(F.col("rho") / F.col("pd")).alias("pd_ratio"))


def gain(errors: DataFrame, keys: list[str], best: str = "par_bt") -> DataFrame:
    """keys, method, gain_t1, gain_t2: each method's error over the best one's."""
    b = errors.filter(F.col("method") == best).select(*keys, F.col("err_t1").alias("b1"), F.col("err_t2").alias("b2"))
    return errors.filter(F.col("method") != best).join(b, keys).select(*keys, "method", (F.col("err_t1") / F.col("b1")).alias("gain_t1"), (F.col("err_t2") / F.col("b2")).alias("gain_t2"))


def ringing(maps: DataFrame, rois: DataFrame, keys: list[str]) -> DataFrame:
    """keys, roi_id, ringing: total variation of T1 inside flat regions."""
    m = maps.join(F.broadcast(rois.filter("roi_id is not null").select("row", "col", "roi_id", "n_nationkey")), ["row", "col"])
    step = lambda over, along: F.coalesce(F.lead("t1").over(Window.partitionBy(*keys, "n_nationkey", over).orderBy(along)) - F.col("t1"), F.lit(0.0))
    return m.withColumns({"_d": step("col", "row"), "_r": step("row", "col")}).groupBy(*keys, "roi_id").agg(F.sum(F.hypot("_d", "_r")).alias("ringing"))


def best_iterate(history: DataFrame, keys: list[str]) -> DataFrame:
    """keys, iter, fidelity, attempts: the accepted iterate of lowest fidelity."""
    done = history.filter("accepted").groupBy(*keys).agg(F.min_by("iter", F.struct("fidelity", "iter")).alias("iter"), F.min("fidelity").alias("fidelity"))
    return done.join(history.groupBy(*keys).agg(F.count("*").alias("attempts")), keys)


def working_set(n: int, rank: int, length: int, samples: int, interleaves: int) -> dict[str, float]:
    """Coefficients and single-precision bytes: compressed image against the
    time-mixing baseline's k-space."""
    own, mixed = n * n * rank, length * samples * interleaves
    return {"own_values": own, "mixed_values": mixed, "own_mb": own * 8 / 1e6, "mixed_mb": mixed * 8 / 1e6}


def working_set_table(configs: DataFrame) -> DataFrame:
    """Adds the columns of :func:`working_set` to (n, rank, length, samples, interleaves)."""
    own = (F.col("n") * F.col("n") * F.col("rank")).cast("long")
    mixed = (F.col("length").cast("long") * F.col("samples") * F.col("interleaves")).cast("long")
    return configs.select("n", "rank", "length", own.alias("own_values"), mixed.alias("mixed_values"), (own * 8 / 1e6).alias("own_mb"), (mixed * 8 / 1e6).alias("mixed_mb"))
