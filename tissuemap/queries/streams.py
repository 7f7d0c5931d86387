"""Queries of the streaming operators; each equals its batch twin in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..streaming import streams as st
from .model import q6, r6

#: Cells of the running adjoint matched to the hours: slice, cell, atom_id, rho.
HOUR_MAPS = """WITH c AS (SELECT user_id AS slice, (props->>'k')::INTEGER AS cell, j::INTEGER AS comp, sum(value * cos(pi() * (hour(ts) + 0.5) * j / 24)) AS v FROM events, range(3) r(j) GROUP BY ALL),
ha AS (SELECT h::BIGINT AS atom_id, j::INTEGER AS comp, cos(pi() * (h + 0.5) * j / 24) AS a FROM range(24) x(h), range(3) r(j)),
s AS (SELECT slice, cell, atom_id, sum(v * a) AS dot, sum(a * a) AS n2 FROM c JOIN ha USING (comp) GROUP BY ALL),
best AS (SELECT slice, cell, atom_id, greatest(dot / n2, 0) AS rho FROM s QUALIFY row_number() OVER (PARTITION BY slice, cell ORDER BY round(abs(dot) / sqrt(n2), 9) DESC, atom_id) = 1)"""
_STAMP = "strftime({0}, '%Y-%m-%d %H:%M:%S')"


def _stamp(c: str):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias(c)


def j02_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = st.source(spark, sf_dir).withWatermark("ts", "10 minutes")
    return st.drain(st.tumbling(s), "update", ["slice", "day"]).select("slice", _stamp("day"), "n", *r6("power"))


def j03_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.drain(st.sliding(st.source(spark, sf_dir).withWatermark("ts", "10 minutes")), "update", ["start"]).select(_stamp("start"), "n")


def j04_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The batch form of the session window (a stream closes its last sessions
    only when the watermark passes them)."""
    from ..sources.tables import stream_samples

    return st.sessions(stream_samples(spark, sf_dir)).select("slice", _stamp("start"), "n")


def j05_running_adjoint(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = st.drain(st.running_adjoint(st.source(spark, sf_dir)), "update", ["slice", "cell", "comp"])
    return out.select("slice", "cell", "comp", *r6("v"))


def j06_tracked_slices(spark: SparkSession, sf_dir: str) -> DataFrame:
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return st.drain(st.tracked(st.source(spark, sf_dir), 60)).select("slice", "n", "cell", "atom_id", *r6("rho"))
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)


def j07_stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.drain(st.calibrated(st.source(spark, sf_dir)))


def j08_unique(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.drain(st.unique(st.source(spark, sf_dir))).agg(F.count("*").alias("n"), F.count_distinct("event_id").alias("ids"))


QUERIES = {f.__name__: f for f in (j02_tumbling, j03_sliding, j04_sessions, j05_running_adjoint, j06_tracked_slices, j07_stream_join, j08_unique)}
SQL = {
    "j02_tumbling": f"SELECT user_id AS slice, {_STAMP.format('date_trunc($day$day$day$, ts)')} AS day, count(*) AS n, {q6('sum(value * value)', 'power')} FROM events GROUP BY ALL".replace("$day$day$day$", "'day'"),
    "j03_sliding": f"SELECT {_STAMP.format('s')} AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - i * INTERVAL 6 HOUR AS s FROM events, range(4) r(i)) GROUP BY ALL",
    "j04_sessions": f"""WITH o AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
g AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM o) SELECT user_id AS slice, {_STAMP.format('min(ts)')} AS start, count(*) AS n FROM g GROUP BY user_id, k""",
    "j05_running_adjoint": f"SELECT user_id AS slice, (props->>'k')::INTEGER AS cell, j::INTEGER AS comp, {q6('sum(value * cos(pi() * (hour(ts) + 0.5) * j / 24))', 'v')} FROM events, range(3) r(j) GROUP BY ALL",
    "j06_tracked_slices": f"{HOUR_MAPS}, full_ AS (SELECT user_id AS slice, count(*) AS n FROM events GROUP BY user_id HAVING count(*) >= 60) SELECT slice, n, cell, atom_id, {q6('rho', 'rho')} FROM best JOIN full_ USING (slice)",
    "j07_stream_join": "SELECT a.event_id AS view, b.event_id AS click FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
    "j08_unique": "SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events",
}
