"""Further methods and operators: step rules by name, regression instead of
matching, neighbour joins, Arrow functions, stream to maps."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import EngineConfig
from ..operators import dictionary, phantom, sequence, spatial
from ..plans import metrics
from ..plans.setup import make
from ..plans.slices import phantom_samples, reduce_samples, run_slices
from ..sources import raw_frames, tables
from ..streaming import streams as st
from . import fixtures as fx
from .model import q6, r6
from .streams import HOUR_MAPS

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


def _history(spark: SparkSession, methods, **settings) -> DataFrame:
    s = make(16, 60, 10, 1.5, 3.0, every=10)
    state = reduce_samples(phantom_samples(spark, phantom.digital(spark, 16), 16, 60, s.mask), [s])
    return run_slices(state, [s], methods, EngineConfig(lam=2e-3, **settings), history=True)


@query()
def a51_fixed_and_backtracking(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Steps of the two rules side by side."""
    h = _history(spark, ["seq_fixed", "seq_bt"], k_max=6)
    return h.groupBy("method", "iter").agg(F.count("*").alias("attempts"), F.max("step").alias("first_step"), F.min("step").alias("taken_step")).select("method", "iter", "attempts", *r6("first_step", "taken_step"))


@query()
def c6_iterations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Iterations and attempts to the best fidelity."""
    return metrics.best_iterate(_history(spark, ["seq_fixed", "seq_bt", "par_bt"]), ["method"]).select("method", "iter", "attempts", *r6("fidelity"))


@query()
def a39b_regression(spark: SparkSession, sf_dir: str) -> DataFrame:
    """T1 and T2 by ridge regression on squared compressed signals, where matching
    would search: every atom is predicted by a model that learned from the other
    four fifths; mean relative errors."""
    from ..operators.subspace import leading

    params = dictionary.param_grid(spark)
    atoms = dictionary.build(params, sequence.pulse_schedule(spark, 60)).select("atom_id", "t1", "t2", "sig", "norm").toPandas()  # the grid: 5366 atoms
    x = np.array(atoms["sig"].tolist()) / atoms["norm"].to_numpy()[:, None]
    x = x @ leading(x.T @ x, 8)[1]
    pairs = np.triu_indices(8)
    x = np.column_stack([np.ones(len(x)), x, x[:, pairs[0]] * x[:, pairs[1]]])
    y = np.log(atoms[["t1", "t2"]].to_numpy())
    fold, err = atoms["atom_id"].to_numpy() % 5, np.zeros_like(y)
    for k in range(5):
        a, b = x[fold != k], y[fold != k]
        w = np.linalg.solve(a.T @ a + 1e-8 * np.eye(x.shape[1]), a.T @ b)
        err[fold == k] = np.abs(np.exp(x[fold == k] @ w - y[fold == k]) - 1)
    return spark.createDataFrame([(len(x), *(round(float(v), 6) for v in err.mean(axis=0)))], "atoms int, err_t1 double, err_t2 double")


@query(f"WITH RECURSIVE {fx.SQL_SCAN}, {fx.SQL_TRUTH} SELECT o.row, o.col, o.comp, {q6('coalesce(d.re - o.re, 0)', 'dre_r')} FROM img o LEFT JOIN img d ON d.row = o.row + 1 AND d.col = o.col AND d.comp = o.comp")
def f11_neighbour_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spatial.neighbour_differences(fx.truth(spark)).select("row", "col", "comp", *r6("dre_r"))


@query(f"SELECT event_id, {q6('value * value + 1', 'y')} FROM events")
def i02_arrow_function(spark: SparkSession, sf_dir: str) -> DataFrame:
    import pyarrow as pa
    import pyarrow.compute as pc

    def squared(v):
        return pc.add(pc.multiply(v, v), 1.0)

    squared.__annotations__ = {"v": pa.Array, "return": pa.Array}
    f = F.arrow_udf(squared, "double")
    return tables.read(spark, sf_dir, "events").select("event_id", f("value").alias("y")).select("event_id", *r6("y"))


@query("SELECT p_brand, count(*) AS parts, (SELECT count(*) FROM lineitem JOIN part q ON l_partkey = q.p_partkey WHERE q.p_brand = p.p_brand) AS lines FROM part p GROUP BY p_brand")
def i03_cogroup(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = tables.read(spark, sf_dir, "part").select("p_partkey", "p_brand")
    li = tables.read(spark, sf_dir, "lineitem").select("l_partkey").join(p, F.col("l_partkey") == F.col("p_partkey")).select(F.col("p_brand").alias("b"), "l_partkey")

    def both(key, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"p_brand": [key[0]], "parts": [len(left)], "lines": [len(right)]})

    return p.groupBy("p_brand").cogroup(li.groupBy("b")).applyInPandas(both, "p_brand string, parts long, lines long")


@query("SELECT e.vec_id, e.label, n.higher FROM embeddings e, LATERAL (SELECT count(*) AS higher FROM embeddings x WHERE x.label = e.label AND x.vec_id > e.vec_id) n")
def f12_lateral(spark: SparkSession, sf_dir: str) -> DataFrame:
    tables.read(spark, sf_dir, "embeddings").select("vec_id", "label").createOrReplaceTempView("tm_labels")
    return spark.sql("SELECT e.vec_id, e.label, n.higher FROM tm_labels e, LATERAL (SELECT count(*) AS higher FROM tm_labels x WHERE x.label = e.label AND x.vec_id > e.vec_id) n")


@query(f"{HOUR_MAPS} SELECT slice, cell, atom_id, {q6('rho', 'rho')} FROM best")
def w14_stream_maps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The running adjoint of the stream, matched after the last batch."""
    cells = st.drain(st.running_adjoint(st.source(spark, sf_dir)), "update", ["slice", "cell", "comp"])
    return st.maps(cells).select("slice", "cell", "atom_id", *r6("rho"))


@query(
    f"""SELECT user_id AS slice_id, CASE event_type WHEN 'view' THEN 0 WHEN 'click' THEN 1 ELSE 2 END AS coil, hour(ts)::INTEGER AS t, (props->>'k')::INTEGER AS ku, day(ts)::INTEGER AS kv,
count(*) AS n, round(sum(value::FLOAT::DOUBLE), 4) + 0.0 AS re, round(sum(-(value::FLOAT::DOUBLE)), 4) + 0.0 AS im FROM events GROUP BY ALL"""
)
def e07_raw_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events written as binary frames and read back, added up by sample."""
    back = raw_frames.parse(raw_frames.pack(raw_frames.event_samples(tables.read(spark, sf_dir, "events"))))
    sums = [F.round(F.sum(F.col(c).cast("double")), 4).alias(c) for c in ("re", "im")]
    return back.groupBy("slice_id", "coil", "t", "ku", "kv").agg(F.count("*").alias("n"), *sums)


@query("SELECT count(*) AS rows, count(DISTINCT user_id) AS slices FROM events")
def j10_observed_metrics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts that a query reports while it runs, without a second pass."""
    from pyspark.sql import Observation

    o = Observation("samples")
    e = tables.read(spark, sf_dir, "events").observe(o, F.count("*").alias("rows"))
    slices = e.agg(F.count_distinct("user_id").alias("slices")).first()["slices"]
    return spark.createDataFrame([(o.get["rows"], slices)], "rows long, slices long")


@query(
    """WITH w AS (SELECT max(ts) - INTERVAL 10 MINUTE AS mark FROM events WHERE event_id % 2 = 0),
e AS (SELECT event_id % 2 = 1 AND date_trunc('day', ts) + INTERVAL 1 DAY <= mark AS late FROM events, w)
SELECT count(*) FILTER (late) AS late, count(*) FILTER (NOT late) AS kept FROM e"""
)
def j01_watermark(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that a watermark drops: odd events arrive after the even ones, and those
    of days that the watermark has passed by then are late."""
    plan = lambda s: st.tumbling(s.withWatermark("ts", "10 minutes"))
    n = st.in_two_batches(spark, sf_dir, F.col("event_id") % 2 == 1, plan, "update", ["slice", "day"]).agg(F.sum("n").alias("kept"))
    total = tables.read(spark, sf_dir, "events").agg(F.count("*").alias("total"))
    return n.crossJoin(total).select((F.col("total") - F.col("kept")).alias("late"), "kept")
