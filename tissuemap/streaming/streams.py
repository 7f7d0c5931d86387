"""Streams of readouts: windows, late rows, running adjoint, per-slice state."""

from __future__ import annotations

import math
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions.cx import v_dot
from ..operators import matching
from ..sources.scratch import folder
from ..sources.schemas import TABLES, schema
from ..sources.tables import acquisition


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events`` as a file stream of readouts."""
    return acquisition(spark.readStream.schema(schema(TABLES["events"])).parquet(f"{sf_dir}/events.parquet*"))


def drain(stream: DataFrame, mode: str = "append", keys: list[str] | None = None, base: str | None = None) -> DataFrame:
    """Run over what is there, into a written table; in update mode the last
    version of each key counts. A later call with the same ``base`` goes on from
    the state, the watermark and the rows of the one before."""
    spark = stream.sparkSession
    base = base or f"{folder(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        batch.withColumn("_batch", F.lit(number)).write.mode("append").parquet(f"{base}/rows")

    q = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{base}/state").foreachBatch(write).start()
    q.awaitTermination()
    from pyspark.sql import types as T

    shape = T.StructType([*stream.schema.fields, T.StructField("_batch", T.IntegerType())])
    rows = spark.read.schema(shape).parquet(f"{base}/rows")
    if mode == "update" and keys:
        last = [F.max_by(c, "_batch").alias(c) for c in stream.columns if c not in keys]
        return rows.groupBy(*keys).agg(*last)
    return rows.drop("_batch")


def in_two_batches(spark: SparkSession, sf_dir: str, second: Column, plan, mode: str, keys: list[str]) -> DataFrame:
    """The events as two arrivals of one stream, those marked by ``second`` later."""
    base = f"{folder(spark)}/arrivals-{uuid.uuid4().hex}"
    events = spark.read.schema(schema(TABLES["events"])).parquet(f"{sf_dir}/events.parquet*")
    for part in (~second, second):
        events.filter(part).write.mode("append").parquet(f"{base}/events")
        stream = acquisition(spark.readStream.schema(events.schema).parquet(f"{base}/events"))
        out = drain(plan(stream), mode, keys, f"{base}/run")
    return out


def tumbling(samples: DataFrame) -> DataFrame:
    """slice, day start, n, power per day."""
    return samples.groupBy("slice", F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"), F.sum(F.col("value") ** 2).alias("power")).select("slice", F.col("w.start").alias("day"), "n", "power")


def sliding(samples: DataFrame) -> DataFrame:
    return samples.groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(samples: DataFrame) -> DataFrame:
    """Bursts of readouts of a slice with gaps below two hours."""
    return samples.groupBy("slice", F.session_window("ts", "2 hours").alias("w")).agg(F.count("*").alias("n")).select("slice", F.col("w.start").alias("start"), "n")


def running_adjoint(samples: DataFrame, rank: int = 3) -> DataFrame:
    """Per slice, cell and component the sum of samples in a cosine basis of the
    hour: Aᴴy is a sum over readouts, so it can be kept up to date."""
    comp = F.explode(F.array(*[F.lit(j) for j in range(rank)])).alias("comp")
    x = samples.select("slice", "cell", "value", F.hour("ts").alias("t"), comp)
    b = F.cos(math.pi * (F.col("t") + 0.5) * F.col("comp") / 24)
    return x.groupBy("slice", "cell", "comp").agg(F.sum(F.col("value") * b).alias("v"))


def hour_atoms(rank: int = 3) -> np.ndarray:
    """24 x rank: what a readout at each hour gives in the cosine basis."""
    return np.cos(np.pi * (np.arange(24)[:, None] + 0.5) * np.arange(rank) / 24)


def maps(cells: DataFrame, rank: int = 3) -> DataFrame:
    """slice, cell, atom_id, rho: the running adjoint (slice, cell, comp, v) matched
    to the 24 hours."""
    packed = cells.groupBy(F.struct("slice", "cell").alias("id")).agg(F.transform(F.sort_array(F.collect_list(F.struct("comp", "v"))), lambda x: x["v"]).alias("x"))
    rows = [(h, [float(v) for v in line]) for h, line in enumerate(hour_atoms(rank))]
    atoms = matching.with_norm(cells.sparkSession.createDataFrame(rows, "id long, x array<double>"))
    best = matching.exhaustive_join(packed, atoms, "absolute", keep=True)
    rho = F.greatest(v_dot(F.col("x"), F.col("a")) / (F.col("norm") * F.col("norm")), F.lit(0.0))
    return best.select("id.slice", "id.cell", "atom_id", rho.alias("rho"))


class SliceTracker(StatefulProcessor):
    """Adds up the readouts of a slice per cell and component; once it is complete
    its cells are matched and given out. With ``patience``, a slice that stays
    incomplete for so many milliseconds is given out as it is."""

    def __init__(self, wanted: int, patience: int | None = None, rank: int = 3) -> None:
        self.wanted, self.patience, self.rank = wanted, patience, rank

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.state = handle.getValueState("progress", "n long, cells array<int>, sums array<double>, done boolean")

    def _maps(self, slice_id: int, n: int, cells: list, sums: list) -> pd.DataFrame:
        x, a = np.array(sums, float).reshape(len(cells), self.rank), hour_atoms(self.rank)
        norm = np.linalg.norm(a, axis=1)
        at = np.round(np.abs(x @ a.T) / norm, matching.DIGITS).argmax(axis=1)
        rho = np.maximum((x * a[at]).sum(axis=1) / norm[at] ** 2, 0)
        return pd.DataFrame({"slice": slice_id, "n": n, "cell": np.array(cells, np.int32), "atom_id": at, "rho": rho})

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        n, cells, sums, done = self.state.get() if self.state.exists() else (0, [], [], False)
        held = dict(zip(cells, np.array(sums, float).reshape(len(cells), self.rank), strict=True))
        for pdf in rows:
            n += len(pdf)
            given = pdf["value"].to_numpy()[:, None] * hour_atoms(self.rank)[pdf["hour"].to_numpy()]
            for cell, line in zip(pdf["cell"].tolist(), given, strict=True):
                held[cell] = held.get(cell, 0) + line
        cells, sums = list(held), [float(v) for line in held.values() for v in line]
        if not done:
            if n >= self.wanted:
                done = True
                yield self._maps(key[0], n, cells, sums)
            elif self.patience:
                self.handle.registerTimer(timerValues.getCurrentProcessingTimeInMs() + self.patience)
        self.state.update((int(n), [int(c) for c in cells], sums, bool(done)))

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        n, cells, sums, done = self.state.get() if self.state.exists() else (0, [], [], True)
        if not done:
            self.state.update((n, cells, sums, True))
            yield self._maps(key[0], n, cells, sums)

    def close(self) -> None:
        pass


def tracked(samples: DataFrame, wanted: int, patience: int | None = None) -> DataFrame:
    """slice, n, cell, atom_id, rho: the maps of a slice once it has ``wanted``
    readouts. Needs the RocksDB state store. With ``patience`` timers run, and the
    query goes on until the last of them has expired: for streams that stay open."""
    rows = samples.select("slice", "cell", "value", F.hour("ts").alias("hour"))
    return rows.groupBy("slice").transformWithStateInPandas(SliceTracker(wanted, patience), "slice long, n long, cell int, atom_id long, rho double", "append", "ProcessingTime" if patience else "None")


def calibrated(samples: DataFrame) -> DataFrame:
    """Clicks joined to the views of the same slice in the hour before."""
    a = samples.filter("coil = 'view'").select("slice", F.col("event_id").alias("view"), F.col("ts").alias("at")).withWatermark("at", "10 minutes")
    b = samples.filter("coil = 'click'").select(F.col("slice").alias("s2"), F.col("event_id").alias("click"), F.col("ts").alias("then")).withWatermark("then", "10 minutes")
    near = (F.col("slice") == F.col("s2")) & (F.col("then") > F.col("at")) & (F.col("then") <= F.col("at") + F.expr("INTERVAL 1 HOUR"))
    return a.join(b, near).select("view", "click")


def unique(samples: DataFrame) -> DataFrame:
    return samples.withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"])
