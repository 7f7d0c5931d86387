"""Queries of the operators around the methods: relational, scalar, nested."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import cx
from ..operators import joins
from ..sources import tables
from ..sources.scratch import folder
from . import fixtures as fx
from .model import q6, r6

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


def rd(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return tables.read(spark, sf_dir, name)


@query("SELECT l_returnflag, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem WHERE l_quantity >= 45 AND l_discount < 0.03 GROUP BY l_returnflag")
def e01_pushed_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = rd(spark, sf_dir, "lineitem").filter((F.col("l_quantity") >= 45) & (F.col("l_discount") < 0.03))
    return li.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


@query("SELECT count(*) AS n, sum(p_size) AS sizes FROM part WHERE p_brand = (SELECT min(p_brand) FROM part)")
def e02_partitioned_sink(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Written by brand and read back with one partition."""
    import uuid

    path = f"{folder(spark)}/parts-{uuid.uuid4().hex}"
    p = rd(spark, sf_dir, "part")
    p.select("p_partkey", "p_size", "p_brand").repartition("p_brand").write.partitionBy("p_brand").parquet(path)
    first = p.agg(F.min("p_brand")).first()[0]
    back = spark.read.schema("p_partkey bigint, p_size int, p_brand string").parquet(path).filter(F.col("p_brand") == first)
    return back.agg(F.count("*").alias("n"), F.sum("p_size").alias("sizes"))


@query("SELECT p_type, count(*) AS n, sum(p_size) AS sizes FROM part GROUP BY p_type")
def e03_format_round_trips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same rows through JSON lines, CSV and ORC in turn."""
    import uuid

    df, shape = rd(spark, sf_dir, "part").select("p_partkey", "p_type", "p_size"), "p_partkey bigint, p_type string, p_size int"
    for kind in ("json", "csv", "orc"):
        path = f"{folder(spark)}/{kind}-{uuid.uuid4().hex}"
        df.write.format(kind).save(path)
        df = spark.read.schema(shape).format(kind).load(path)
    return df.groupBy("p_type").agg(F.count("*").alias("n"), F.sum("p_size").alias("sizes"))


@query(f"WITH {fx.sql_phantom(32)} SELECT class, count(*) AS voxels FROM ph GROUP BY class")
def e05_phantom_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..sources.phantom_source import register

    register(spark)
    return spark.read.format("phantom").option("n", "32").load().groupBy("class").agg(F.count("*").alias("voxels"))


@query("SELECT c_mktsegment, count(*) AS n FROM customer WHERE c_acctbal > 0 GROUP BY c_mktsegment")
def e06_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    rd(spark, sf_dir, "customer").createOrReplaceTempView("tm_customer")
    return spark.sql("SELECT c_mktsegment, count(*) AS n FROM tm_customer WHERE c_acctbal > 0 GROUP BY c_mktsegment")


@query("SELECT l_orderkey, l_linenumber, l_partkey // 50 AS grid_row, l_partkey % 50 AS grid_col FROM lineitem")
def f01_grid_coordinates(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = F.col("l_partkey")
    return rd(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", F.floor(k / 50).alias("grid_row"), (k % 50).alias("grid_col"))


@query("SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20 AND (p_type LIKE '%A%' OR p_brand IN ('Brand#11', 'Brand#12')) AND p_name IS NOT DISTINCT FROM p_name")
def f02_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = rd(spark, sf_dir, "part")
    return p.filter(F.col("p_size").between(10, 20) & (F.col("p_type").like("%A%") | F.col("p_brand").isin("Brand#11", "Brand#12")) & F.col("p_name").eqNullSafe(F.col("p_name"))).select("p_partkey")


@query("SELECT p_brand, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def f03_lookup_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The size of ``part`` decides by itself between broadcast and shuffle."""
    li, p = rd(spark, sf_dir, "lineitem").select("l_partkey", "l_quantity"), rd(spark, sf_dir, "part").select("p_partkey", "p_brand")
    return li.join(p, li.l_partkey == p.p_partkey).groupBy("p_brand").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


_OL = "SELECT o_orderpriority, count(*) AS n, sum(l_quantity) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority"


@query(_OL)
def f04_merge_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o = rd(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity"), rd(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    return li.join(o.hint("MERGE"), li.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


@query(_OL)
def f04_hash_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o = rd(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity"), rd(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    return li.join(o.hint("SHUFFLE_HASH"), li.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


@query("SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey")
def f05_theta_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = rd(spark, sf_dir, "nation")
    a, b = n.select(F.col("n_nationkey").alias("a"), "n_regionkey"), n.select(F.col("n_nationkey").alias("b"), "n_regionkey")
    return a.join(b, "n_regionkey").filter("a < b").select("a", "b")


@query("WITH b AS (SELECT i::INTEGER AS bin, 900 + 37.5 * i AS lo, 900 + 37.5 * (i + 1) AS hi FROM range(40) r(i)) SELECT bin, count(*) AS n FROM part JOIN b ON p_retailprice >= lo AND p_retailprice < hi GROUP BY bin")
def f06_range_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    bins = spark.range(40).select(F.col("id").cast("int").alias("bin"), (900 + 37.5 * F.col("id")).alias("lo"), (900 + 37.5 * (F.col("id") + 1)).alias("hi"))
    return joins.in_bins(rd(spark, sf_dir, "part").select("p_retailprice"), bins, "p_retailprice", "lo", "hi", 25.0).groupBy("bin").agg(F.count("*").alias("n"))


@query("WITH c AS (SELECT user_id, ts, max(event_id) AS calibration FROM events WHERE event_type = 'signup' GROUP BY ALL) SELECT e.event_id, (SELECT arg_max(c.calibration, c.ts) FROM c WHERE c.user_id = e.user_id AND c.ts <= e.ts) AS calibration FROM events e WHERE event_type = 'view'")
def f07_as_of_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = rd(spark, sf_dir, "events")
    cal = e.filter("event_type = 'signup'").groupBy("user_id", "ts").agg(F.max("event_id").alias("calibration"))
    return joins.as_of(e.filter("event_type = 'view'").select("event_id", "user_id", "ts"), cal, "user_id", "ts", "calibration").select("event_id", "calibration")


@query("SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def f08_interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = rd(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    a, b = e.select("user_id", F.col("event_id").alias("first"), F.col("ts").alias("lt")), e.select("user_id", F.col("event_id").alias("second"), F.col("ts").alias("rt"))
    return joins.within(a, b, "user_id", 3600, "lt", "rt").select("first", "second")


@query("SELECT count(d.doc_id) AS docs, count(l.doc_id) AS labels, count(*) AS n FROM documents d FULL JOIN labels l USING (doc_id)")
def f09_outer_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = rd(spark, sf_dir, "documents").select(F.col("doc_id").alias("d"))
    l = rd(spark, sf_dir, "labels").select(F.col("doc_id").alias("l"))
    return d.join(l, F.col("d") == F.col("l"), "full").agg(F.count("d").alias("docs"), F.count("l").alias("labels"), F.count("*").alias("n"))


@query("SELECT lang, 'in' AS side, count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels) GROUP BY lang UNION ALL SELECT lang, 'out', count(*) FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels) GROUP BY lang")
def f10_semi_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, l = rd(spark, sf_dir, "documents").select("doc_id", "lang"), rd(spark, sf_dir, "labels").select("doc_id")
    part = lambda how, side: d.join(l, "doc_id", how).groupBy("lang").agg(F.count("*").alias("n")).select("lang", F.lit(side).alias("side"), "n")
    return part("left_semi", "in").unionByName(part("left_anti", "out"))


@query("SELECT conv_id, count(*) AS turns, sum(length(text)) AS chars, list_aggregate(list(role ORDER BY turn), 'string_agg', '>') AS roles FROM conversations GROUP BY conv_id")
def f12_nested(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = rd(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("t"))
    each = c.select("conv_id", "t", F.explode("t").alias("x")).groupBy("conv_id").agg(F.count("*").alias("turns"), F.sum(F.length("x.text")).cast("decimal(38,0)").cast("long").alias("chars"), F.array_join(F.transform(F.first("t"), lambda v: v["role"]), ">").alias("roles"))
    return each


@query("SELECT l_returnflag, arg_max(l_orderkey, (l_extendedprice, l_orderkey)) AS top_order, min(l_linestatus) AS first_status, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag")
def f13_aggregates(spark: SparkSession, sf_dir: str) -> DataFrame:
    top = F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey"))
    return rd(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(top.alias("top_order"), F.min("l_linestatus").alias("first_status"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("SELECT true AS within_bound")
def f14_approximate_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = rd(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("b"))
    return x.select((F.abs(F.col("a") - F.col("b")) <= 0.08 * F.col("b")).alias("within_bound"))


@query(f"SELECT o_orderstatus, o_orderpriority, grouping(o_orderstatus, o_orderpriority)::BIGINT AS gid, {q6('avg(o_totalprice)', 'mean')}, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def f15_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = joins.rollup_errors(rd(spark, sf_dir, "orders"), ["o_orderstatus", "o_orderpriority"], "o_totalprice")
    return out.select("o_orderstatus", "o_orderpriority", F.col("gid").cast("long").alias("gid"), *r6("mean"), "n")


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def f15_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rd(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("SELECT user_id, event_type, count(*) AS n FROM events WHERE event_type IN ('view', 'click') GROUP BY ALL")
def f16_pivot_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = rd(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["view", "click"]).count()
    return p.unpivot(["user_id"], ["view", "click"], "event_type", "n").filter("n is not null")


@query(
    f"""SELECT l_returnflag, {q6('stddev_pop(l_quantity)', 'sd')}, {q6('var_samp(l_quantity)', 'var')}, {q6('corr(l_quantity, l_extendedprice)', 'corr')}, {q6('covar_pop(l_quantity, l_tax)', 'cov')},
{q6('quantile_cont(l_quantity, 0.25)', 'q1')}, {q6('median(l_quantity)', 'med')} FROM lineitem GROUP BY l_returnflag"""
)
def f17_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = rd(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(
        F.stddev_pop("l_quantity").alias("sd"), F.var_samp("l_quantity").alias("var"), F.corr("l_quantity", "l_extendedprice").alias("corr"), F.covar_pop("l_quantity", "l_tax").alias("cov"),
        F.percentile("l_quantity", 0.25).alias("q1"), F.median("l_quantity").alias("med"),
    )
    return out.select("l_returnflag", *r6("sd", "var", "corr", "cov", "q1", "med"))


@query("SELECT true AS hll_ok, true AS quantile_ok")
def f18_sketches(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = rd(spark, sf_dir, "events")
    x = e.agg(F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("a"), F.count_distinct("user_id").alias("b"), F.percentile_approx("value", 0.5, 1000).alias("m"), F.median("value").alias("t"))
    return x.select((F.abs(F.col("a") - F.col("b")) <= 0.05 * F.col("b") + 1).alias("hll_ok"), (F.abs(F.col("m") - F.col("t")) <= 0.05 * F.abs(F.col("t")) + 1).alias("quantile_ok"))


@query(
    f"""SELECT p_partkey, row_number() OVER w AS rn, rank() OVER b AS rk, dense_rank() OVER b AS dr, ntile(4) OVER w AS quarter, {q6('percent_rank() OVER b', 'pr')}, {q6('cume_dist() OVER b', 'cd')}
FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey), b AS (PARTITION BY p_brand ORDER BY p_size)"""
)
def f19_ranking(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, b = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    out = rd(spark, sf_dir, "part").select(
        "p_partkey", F.row_number().over(w).alias("rn"), F.rank().over(b).alias("rk"), F.dense_rank().over(b).alias("dr"), F.ntile(4).over(w).alias("quarter"),
        F.percent_rank().over(b).alias("pr"), F.cume_dist().over(b).alias("cd"),
    )
    return out.select("p_partkey", "rn", "rk", "dr", "quarter", *r6("pr", "cd"))


@query("SELECT o_orderkey, lag(o_totalprice) OVER w AS before, lead(o_totalprice) OVER w AS after, first_value(o_orderkey) OVER w AS first, nth_value(o_orderkey, 2) OVER w AS second FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def f20_analytic(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return rd(spark, sf_dir, "orders").select("o_orderkey", F.lag("o_totalprice").over(w).alias("before"), F.lead("o_totalprice").over(w).alias("after"), F.first("o_orderkey").over(w).alias("first"), F.nth_value("o_orderkey", 2).over(w).alias("second"))


@query(
    f"""SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS day_count,
{q6('sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)', 'last3')} FROM events"""
)
def f21_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = rd(spark, sf_dir, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    day = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    last = Window.partitionBy("user_id").orderBy("us", "event_id").rowsBetween(-2, 0)
    return e.select("event_id", F.count("*").over(day).alias("day_count"), F.sum("value").over(last).alias("last3")).select("event_id", "day_count", *r6("last3"))


@query("SELECT p_brand, p_partkey, p_retailprice FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 3")
def f22_top_per_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return rd(spark, sf_dir, "part").withColumn("rn", F.row_number().over(w)).filter("rn <= 3").select("p_brand", "p_partkey", "p_retailprice")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def f22_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rd(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20)


@query(
    """WITH a AS (SELECT DISTINCT l_partkey AS k FROM lineitem WHERE l_quantity > 48), b AS (SELECT p_partkey AS k FROM part WHERE p_size > 25)
SELECT 'both' AS part, count(*) AS n FROM (SELECT k FROM a INTERSECT SELECT k FROM b) UNION ALL SELECT 'first', count(*) FROM (SELECT k FROM a EXCEPT SELECT k FROM b) UNION ALL SELECT 'any', count(*) FROM (SELECT k FROM a UNION SELECT k FROM b)"""
)
def f23_set_operations(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = rd(spark, sf_dir, "lineitem").filter("l_quantity > 48").select(F.col("l_partkey").alias("k")).distinct()
    b = rd(spark, sf_dir, "part").filter("p_size > 25").select(F.col("p_partkey").alias("k"))
    count = lambda df, name: df.agg(F.count("*").alias("n")).select(F.lit(name).alias("part"), "n")
    return count(a.intersect(b), "both").unionByName(count(a.subtract(b), "first")).unionByName(count(a.union(b).distinct(), "any"))


@query("SELECT o_orderkey FROM orders WHERE ('0x' || substr(md5(o_orderkey::VARCHAR), 1, 8))::BIGINT % 10 = 0")
def f24_keyed_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A tenth of the orders by digest: the same rows in any engine and run."""
    part = F.conv(F.substring(F.md5(F.col("o_orderkey").cast("string")), 1, 8), 16, 10).cast("long")
    return rd(spark, sf_dir, "orders").filter(part % 10 == 0).select("o_orderkey")


@query("SELECT c_custkey, (SELECT max(o_totalprice) FROM orders WHERE o_custkey = c_custkey) AS best FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) AND c_acctbal > (SELECT avg(c_acctbal) FROM customer)")
def f25_subqueries(spark: SparkSession, sf_dir: str) -> DataFrame:
    rd(spark, sf_dir, "orders").createOrReplaceTempView("tm_orders")
    rd(spark, sf_dir, "customer").createOrReplaceTempView("tm_customer")
    return spark.sql("SELECT c_custkey, (SELECT max(o_totalprice) FROM tm_orders WHERE o_custkey = c_custkey) AS best FROM tm_customer WHERE EXISTS (SELECT 1 FROM tm_orders WHERE o_custkey = c_custkey) AND c_acctbal > (SELECT avg(c_acctbal) FROM tm_customer)")


@query("WITH RECURSIVE s(t, v) AS (SELECT 0, 1.0::DOUBLE UNION ALL SELECT t + 1, v * 0.5 + 1 FROM s WHERE t < 8) SELECT t, v FROM s")
def f26_recursive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.sql("WITH RECURSIVE s(t, v) AS (SELECT 0, CAST(1 AS DOUBLE) UNION ALL SELECT t + 1, v * 0.5D + 1 FROM s WHERE t < 8) SELECT t, v FROM s")


@query("SELECT d.lang, count(DISTINCT d.text) AS texts, sum(coalesce(l.toxic, 0))::BIGINT AS toxic, count(*) FILTER (l.doc_id IS NULL) AS unknown FROM documents d LEFT JOIN labels l USING (doc_id) GROUP BY d.lang")
def f27_nulls_and_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = rd(spark, sf_dir, "documents").select("doc_id", "lang", F.md5("text").alias("h"))
    l = rd(spark, sf_dir, "labels").select("doc_id", "toxic", F.lit(1).alias("known"))
    j = d.join(l, "doc_id", "left").na.fill({"toxic": 0})
    return j.groupBy("lang").agg(F.count_distinct("h").alias("texts"), F.sum("toxic").alias("toxic"), F.sum(F.col("known").isNull().cast("int")).alias("unknown"))


@query("SELECT l_suppkey, sum(l_quantity) AS v FROM lineitem GROUP BY l_suppkey")
def f28_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = rd(spark, sf_dir, "lineitem").select("l_suppkey", "l_orderkey", "l_quantity")
    return joins.salted_sum(li, "l_suppkey", F.col("l_quantity"))


@query(f"SELECT event_id, {q6('sin(value) + cos(value) + atan2(value, 2)', 'trig')}, {q6('sqrt(abs(value)) + ln(1 + abs(value)) + exp(-abs(value))', 'growth')}, {q6('floor(value) + ceil(value) + sign(value)', 'steps')}, {q6('degrees(radians(value)) + power(value, 2)', 'angles')}, greatest(value, 3.0::DOUBLE) - least(value, 3.0::DOUBLE) AS spread FROM events")
def g01_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = F.col("value")
    out = rd(spark, sf_dir, "events").select(
        "event_id", (F.sin(v) + F.cos(v) + F.atan2(v, F.lit(2.0))).alias("trig"), (F.sqrt(F.abs(v)) + F.log(1 + F.abs(v)) + F.exp(-F.abs(v))).alias("growth"),
        (F.floor(v) + F.ceil(v) + F.signum(v)).cast("double").alias("steps"), (F.degrees(F.radians(v)) + F.pow(v, F.lit(2))).alias("angles"), (F.greatest(v, F.lit(3.0)) - F.least(v, F.lit(3.0))).alias("spread"),
    )
    return out.select("event_id", *r6("trig", "growth", "steps", "angles"), "spread")


@query("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INTEGER AS days, strftime(o_orderdate::DATE + 30, '%Y-%m-%d') AS later FROM orders")
def g02_dates(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    return rd(spark, sf_dir, "orders").select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("first"), F.datediff(F.to_date(d), F.lit("1995-01-01").cast("date")).alias("days"), F.date_format(F.date_add(F.to_date(d), 30), "yyyy-MM-dd").alias("later"))


@query("SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, lower(substr(url, 1, 5)) AS scheme, length(html)::INTEGER AS size, instr(html, '<p>')::INTEGER AS at, replace(regexp_extract(url, '/([a-z]{2})/', 1), 'e', 'E') AS code, md5(url) AS digest, levenshtein(url, 'https://example.org/')::INTEGER AS edits FROM pages")
def g03_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    u = F.col("url")
    return rd(spark, sf_dir, "pages").select("page_id", F.regexp_extract(u, "://([^/]+)", 1).alias("host"), F.lower(F.substring(u, 1, 5)).alias("scheme"), F.length("html").alias("size"), F.instr("html", "<p>").alias("at"), F.replace(F.regexp_extract(u, "/([a-z]{2})/", 1), F.lit("e"), F.lit("E")).alias("code"), F.md5(u).alias("digest"), F.levenshtein(u, F.lit("https://example.org/")).alias("edits"))


@query(f"SELECT vec_id, {q6('list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))', 'power')}, len(list_filter(embedding, lambda x: x > 0))::INTEGER AS positive, {q6('list_max(embedding)::DOUBLE', 'top')}, list_position(embedding, list_max(embedding))::BIGINT AS at, {q6('list_sort(embedding)[1]::DOUBLE', 'low')} FROM embeddings")
def g04_arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = F.col("embedding")
    d = F.transform(e, lambda x: x.cast("double"))
    out = rd(spark, sf_dir, "embeddings").select("vec_id", cx.v_dot(d, d).alias("power"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"), F.array_max(e).cast("double").alias("top"), F.array_position(e, F.array_max(e)).alias("at"), F.element_at(F.sort_array(e), 1).cast("double").alias("low"))
    return out.select("vec_id", *r6("power"), "positive", *r6("top"), "at", *r6("low"))


@query("SELECT user_id, count(DISTINCT event_type) AS kinds, sum((event_type = 'view')::INTEGER)::BIGINT AS views FROM events GROUP BY user_id")
def g05_maps(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = rd(spark, sf_dir, "events").groupBy("user_id", "event_type").count()
    m = n.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m"))
    return m.select("user_id", F.size(F.map_keys("m")).cast("long").alias("kinds"), F.coalesce(F.col("m")["view"], F.lit(0)).alias("views"))


@query("SELECT event_id, (props->>'k')::INTEGER AS k, (props->>'missing') IS NULL AS absent FROM events")
def g06_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    j = F.parse_json("props")
    return rd(spark, sf_dir, "events").select("event_id", F.variant_get(j, "$.k", "int").alias("k"), F.get_json_object("props", "$.missing").isNull().alias("absent"))


@query("SELECT o_orderkey, CASE WHEN o_orderstatus = 'F' THEN 'done' WHEN o_totalprice > 1000 THEN 'large' ELSE 'other' END AS kind, nullif(o_orderpriority, '1-URGENT') AS priority, try_cast(o_orderstatus AS INTEGER) IS NULL AS text, (o_totalprice::DECIMAL(18,2) * 2)::DOUBLE AS twice FROM orders")
def g07_conditional(spark: SparkSession, sf_dir: str) -> DataFrame:
    kind = F.when(F.col("o_orderstatus") == "F", "done").when(F.col("o_totalprice") > 1000, "large").otherwise("other")
    return rd(spark, sf_dir, "orders").select("o_orderkey", kind.alias("kind"), F.nullif("o_orderpriority", F.lit("1-URGENT")).alias("priority"), F.expr("try_cast(o_orderstatus AS INT) IS NULL").alias("text"), (F.col("o_totalprice").cast("decimal(18,2)") * 2).cast("double").alias("twice"))


@query(
    f"""WITH u AS (SELECT i, (('0x' || substr(md5('0-' || i || '-u'), 1, 13))::BIGINT + 0.5::DOUBLE) / 4503599627370496 AS a, (('0x' || substr(md5('0-' || i || '-v'), 1, 13))::BIGINT + 0.5::DOUBLE) / 4503599627370496 AS b FROM range(500) r(i))
SELECT i AS id, {q6('sqrt(-2 * ln(a)) * cos(2 * pi() * b)', 'x')}, {q6('sqrt(-2 * ln(a)) * sin(2 * pi() * b)', 'y')} FROM u"""
)
def g08_keyed_normal(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = cx.normal_pair(F.lit(0), F.col("id"))
    return spark.range(500).select("id", x.alias("x"), y.alias("y")).select("id", *r6("x", "y"))


@query(f"SELECT event_id, {q6('sqrt(value * value + 9)', 'size')}, {q6('atan2(3, value)', 'angle')}, {q6('value * cos(1) - 3 * sin(1)', 'turned')} FROM events")
def h01_complex(spark: SparkSession, sf_dir: str) -> DataFrame:
    z = cx.cx(F.col("value"), 3.0)
    out = rd(spark, sf_dir, "events").select("event_id", cx.modulus(z).alias("size"), cx.arg(z).alias("angle"), cx.mul(z, cx.expi(F.lit(1.0)))["re"].alias("turned"))
    return out.select("event_id", *r6("size", "angle", "turned"))


@query("SELECT event_id, round(abs(value - 50) / 50, 6) + 0.0 AS err FROM events")
def i01_sql_function(spark: SparkSession, sf_dir: str) -> DataFrame:
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tm_rel_err(est DOUBLE, truth DOUBLE) RETURNS DOUBLE RETURN abs(est - truth) / truth")
    rd(spark, sf_dir, "events").createOrReplaceTempView("tm_events")
    return spark.sql("SELECT event_id, round(tm_rel_err(value, 50.0D), 6) + 0.0D AS err FROM tm_events")


@query("SELECT p_brand, quantile_cont(p_retailprice, 0.5) AS median FROM part GROUP BY p_brand")
def i05_grouped_agg(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A robust spread as a grouped-aggregate function over Arrow batches."""
    import pandas as pd

    def middle(v):
        return float(v.median())

    middle.__annotations__ = {"v": pd.Series, "return": float}
    middle = F.pandas_udf(middle, "double")

    return rd(spark, sf_dir, "part").groupBy("p_brand").agg(middle("p_retailprice").alias("median"))


@query("SELECT vec_id, i::INTEGER AS rank, list_sort(embedding, 'DESC')[i + 1]::DOUBLE AS value FROM embeddings, range(3) r(i)")
def i06_table_function(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The largest entries of an array as a table function in SQL."""
    from ..functions.udtf import register

    register(spark)
    rd(spark, sf_dir, "embeddings").createOrReplaceTempView("tm_vectors")
    return spark.sql("SELECT vec_id, t.rank, t.value FROM tm_vectors, LATERAL top_entries(embedding, 3) t")
