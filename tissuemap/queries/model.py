"""Queries of the model: grid, signals, phantom, sampling, encode, steps, algorithms."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import EngineConfig
from ..operators import dictionary, encode, phantom, sequence, spatial, stepsize
from ..operators.subspace import rank_energy
from ..plans import metrics, relational
from ..sources.tables import read
from . import fixtures as fx

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


def r6(*names: str):
    """Columns rounded to six decimals, without negative zero."""
    return [(F.round(c, 6) + 0.0).alias(c) for c in names]


def q6(expr: str, name: str) -> str:
    return f"round({expr}, 6) + 0.0 AS {name}"


IMG = "row, col, comp, " + q6("re", "re") + ", " + q6("im", "im")


def image_out(df: DataFrame) -> DataFrame:
    return df.select("row", "col", "comp", *r6("re", "im"))


@query("SELECT t1, count(*) AS n_t2, sum(t2) AS sum_t2 FROM (SELECT DISTINCT p_retailprice AS t1 FROM part) a JOIN (SELECT DISTINCT p_size::DOUBLE AS t2 FROM part) b ON t1 >= t2 GROUP BY t1")
def a01_param_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The grid of all prices and sizes of parts."""
    p = read(spark, sf_dir, "part")
    grid = dictionary.pairs_of(p.select(F.col("p_retailprice").alias("t1")), p.select(F.col("p_size").cast("double").alias("t2")))
    return grid.groupBy("t1").agg(F.count("*").alias("n_t2"), F.sum("t2").alias("sum_t2"))


@query(f"SELECT event_id AS t, {q6('13.55 + 1.45 * sin(2 * pi() * event_id / 37)', 'tr_ms')}, {q6('74 * (0.3 + 0.7 * abs(sin(1.7 * (event_id // 25) + 0.6))) * sin(pi() * (event_id % 25) / 25)', 'fa_deg')} FROM events")
def a02_schedule(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pulse of each event, ids taken as time points."""
    return sequence.pulses(read(spark, sf_dir, "events").select(F.col("event_id").alias("t"))).select("t", *r6("tr_ms", "fa_deg"))


_PART = "pp AS (SELECT p_partkey AS atom_id, p_retailprice AS t1, p_size::DOUBLE AS t2 FROM part WHERE p_retailprice >= p_size)"
_CUST = "cp AS (SELECT c_custkey AS atom_id, c_acctbal AS t1, 10.0::DOUBLE * (c_nationkey + 1) AS t2 FROM customer WHERE c_acctbal >= 10 * (c_nationkey + 1))"


def _part_params(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts as atoms: the price is T1, the size T2."""
    p = read(spark, sf_dir, "part").filter(F.col("p_retailprice") >= F.col("p_size"))
    return p.select(F.col("p_partkey").alias("atom_id"), F.col("p_retailprice").alias("t1"), F.col("p_size").cast("double").alias("t2"))


def _customer_params(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers as atoms: the balance is T1, ten times the nation's number, from one, T2."""
    c = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("atom_id"), F.col("c_acctbal").alias("t1"), (10.0 * (F.col("c_nationkey") + 1)).alias("t2"))
    return c.filter("t1 >= t2")


@query(f"WITH RECURSIVE {_PART}, {fx.sql_schedule()}, {fx.sql_signal('pp', 'atom_id', 'sig')} SELECT atom_id, t, {q6('v', 'v')} FROM sig")
def a03_fold_signal(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dictionary.simulate_fold(_part_params(spark, sf_dir), sequence.pulse_schedule(spark, fx.L))
    return out.select("atom_id", F.posexplode("sig").alias("t", "v")).select("atom_id", "t", *r6("v"))


@query(f"WITH RECURSIVE {_CUST}, {fx.sql_schedule()}, {fx.sql_signal('cp', 'atom_id', 'sig', 'spoiled')} SELECT atom_id, t, {q6('v', 'v')} FROM sig")
def a03_spoiled_signal(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dictionary.simulate_fold(_customer_params(spark, sf_dir), sequence.pulse_schedule(spark, fx.L), "spoiled")
    return out.select("atom_id", F.posexplode("sig").alias("t", "v")).select("atom_id", "t", *r6("v"))


@query()
def a04_epg_signal(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = dictionary.build(_part_params(spark, sf_dir), sequence.pulse_schedule(spark, 60), "epg")
    return out.select("atom_id", "t1", "t2", *r6("norm"))


@query(f"WITH RECURSIVE {_CUST}, {fx.sql_schedule()}, {fx.sql_signal('cp', 'atom_id', 'sig')} SELECT atom_id, {q6('sqrt(sum(v * v))', 'norm')} FROM sig GROUP BY atom_id")
def a05_dict_norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dictionary.build(_customer_params(spark, sf_dir), sequence.pulse_schedule(spark, fx.L)).select("atom_id", *r6("norm"))


@query(f"WITH RECURSIVE {_PART}, {fx.sql_schedule()}, {fx.sql_signal('pp', 'atom_id', 'sig')} SELECT atom_id, {q6('sqrt(sum(v * v))', 'norm')} FROM sig GROUP BY atom_id")
def a05_dict_norms_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dictionary.build(_part_params(spark, sf_dir), sequence.pulse_schedule(spark, fx.L)).select("atom_id", *r6("norm"))


@query(f"WITH {fx.sql_phantom(32)} SELECT r_name, count(*) AS voxels, avg(t1) AS t1, avg(t2) AS t2, {q6('avg(pd)', 'pd')} FROM ph JOIN region ON class = r_regionkey GROUP BY r_name")
def a06_phantom(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = read(spark, sf_dir, "region").select(F.col("r_regionkey").alias("class"), "r_name")
    out = phantom.digital(spark, 32).join(F.broadcast(names), "class").groupBy("r_name")
    return out.agg(F.count("*").alias("voxels"), F.avg("t1").alias("t1"), F.avg("t2").alias("t2"), F.avg("pd").alias("pd")).select("r_name", "voxels", "t1", "t2", *r6("pd"))


@query(
    """WITH e AS (SELECT ceil(sqrt(max(p_partkey) + 1))::BIGINT AS n FROM part), m AS (SELECT n, (n * 16 + 26) // 27 AS k FROM e),
o AS (SELECT i // k AS r, i % k AS c, n, k FROM (SELECT n, k, unnest(range(k * k)) AS i FROM m)),
w AS (SELECT r, c, floor((r + 0.5::DOUBLE) * n / k)::BIGINT AS row, floor((c + 0.5::DOUBLE) * n / k)::BIGINT AS col, n FROM o)
SELECT r::INTEGER AS row, c::INTEGER AS col, p_size AS size FROM w JOIN part ON p_partkey = row * n + col"""
)
def a06_resample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The square grid of all parts, resampled to 16/27 of its edge."""
    p = read(spark, sf_dir, "part").select("p_partkey", "p_size")
    last = p.agg(F.ceil(F.sqrt(F.max("p_partkey") + 1))).first()[0] or 1
    grid = p.select(F.floor(F.col("p_partkey") / last).cast("int").alias("row"), (F.col("p_partkey") % last).cast("int").alias("col"), F.col("p_size").alias("size"))
    return phantom.resample_nn(grid, last, -(-last * 16 // 27)).select("row", "col", "size")


@query(
    """WITH px AS (SELECT i // 40 AS row, i % 40 AS col FROM range(1600) r(i)),
d AS (SELECT *, (n_nationkey // 5 + 0.5) * 8 AS cr, (n_nationkey % 5 + 0.5) * 8 AS cc FROM nation),
h AS (SELECT * FROM px JOIN d ON sqrt(power(row + 0.5 - cr, 2) + power(col + 0.5 - cc, 2)) < 0.38 * 8)
SELECT n_regionkey AS roi_id, count(*) AS voxels, """
    + q6("avg(200 + 90 * n_nationkey)", "t1")
    + " FROM h GROUP BY n_regionkey"
)
def a07_inserts(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = phantom.inserts(spark, read(spark, sf_dir, "nation"), 40).filter("roi_id is not null").groupBy("roi_id")
    return out.agg(F.count("*").alias("voxels"), F.avg("t1").alias("t1")).select("roi_id", "voxels", *r6("t1"))


@query("SELECT event_id AS t, round(((event_id - event_id // 48) * 82.5 + (event_id // 48) * 84.0) % 360, 6)::DOUBLE + 0.0 AS angle FROM events")
def a08_spiral_angles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The angle of each event, ids taken as repetitions."""
    return sequence.angles(read(spark, sf_dir, "events").select(F.col("event_id").alias("t"))).select("t", *r6("angle"))


_CUST_MASK = fx.SQL_MASK.replace(f"FROM range({fx.L}) r(t)", "FROM (SELECT c_custkey AS t FROM customer)").replace("t::INTEGER AS t", "t").replace(f"{fx.L}.0::DOUBLE / count(*)", "((SELECT max(t) FROM hits) + 1)::DOUBLE / count(*)")


@query(f"WITH {_CUST_MASK} SELECT t, ku, kv, {q6('w', 'w')} FROM mask")
def a09_mask(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An interleaf for each customer: the cells that it meets, and their weights."""
    turned = sequence.angles(read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("t")))
    return sequence.sampling_mask(sequence.interleaves(turned, fx.N, fx.SAMPLES, fx.INNER, fx.OUTER), fx.N).select("t", "ku", "kv", *r6("w"))


_FORWARD = f"""ims AS (SELECT u.ku::INTEGER AS ku, v.kv::INTEGER AS kv, comp, sum(re * cos(2 * pi() * (row * u.ku + col * v.kv) / 8)) / 8 AS re, -sum(re * sin(2 * pi() * (row * u.ku + col * v.kv) / 8)) / 8 AS im
  FROM img, range(8) u(ku), range(8) v(kv) GROUP BY ALL),
fwd AS (SELECT m.t, m.ku, m.kv, sqrt(any_value(w)) * sum(re * b) AS re, sqrt(any_value(w)) * sum(im * b) AS im FROM mask m JOIN ims ON ims.ku = m.ku AND ims.kv = m.kv JOIN basis b ON b.t = m.t AND b.comp = ims.comp GROUP BY ALL)"""


_PART_IMG = "img AS (SELECT p_partkey // 64 AS slice_id, ((p_partkey % 64) // 8)::INTEGER AS row, (p_partkey % 8)::INTEGER AS col, j::INTEGER AS comp, CASE WHEN j = 0 THEN p_retailprice / 1000 ELSE p_size / 50.0::DOUBLE END AS re, 0.0::DOUBLE AS im FROM part, range(2) c(j))"
_PART_FORWARD = _FORWARD.replace("comp, sum(re * cos", "slice_id, comp, sum(re * cos").replace("SELECT m.t,", "SELECT slice_id, m.t,")


@query(f"WITH {fx.SQL_BASIS}, {fx.SQL_MASK}, {_PART_IMG}, {_PART_FORWARD} SELECT slice_id, t, ku, kv, {q6('re', 're')}, {q6('im', 'im')} FROM fwd")
def a10_forward_dft(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Samples of images of 64 parts each, of two components: price and size."""
    p, key = read(spark, sf_dir, "part"), F.col("p_partkey")
    values = F.explode(F.array(F.struct(F.lit(0).alias("comp"), (F.col("p_retailprice") / 1000).alias("re")), F.struct(F.lit(1).alias("comp"), (F.col("p_size") / 50.0).alias("re")))).alias("v")
    img = p.select(F.floor(key / 64).alias("slice_id"), F.floor(key % 64 / 8).cast("int").alias("row"), (key % 8).cast("int").alias("col"), values)
    img = img.select("slice_id", "row", "col", "v.comp", "v.re", F.lit(0.0).alias("im"))
    return encode.forward(img, fx.N, fx.mask(spark), fx.basis(spark)).select("slice_id", "t", "ku", "kv", *r6("re", "im"))


@query(f"WITH RECURSIVE {fx.SQL_SCAN}, {fx.sql_adjoint()} SELECT {IMG} FROM adj")
def a11_adjoint_dft(spark: SparkSession, sf_dir: str) -> DataFrame:
    return image_out(encode.adjoint(fx.samples(spark), fx.N, fx.mask(spark), fx.basis(spark)))


@query(f"WITH {fx.SQL_BASIS}, {fx.SQL_MASK}, {fx.SQL_KERNEL} SELECT ku, kv, j AS comp, j2 AS comp2, {q6('k', 're')} FROM kern")
def a12_normal_kernel(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode.normal_kernel(fx.mask(spark), fx.basis(spark)).select("ku", "kv", "comp", "comp2", *r6("re"))


@query(f"WITH RECURSIVE {fx.SQL_SCAN}, {fx.SQL_TRUTH}, {fx.SQL_KERNEL}, {fx.sql_normal('img', 'nrm')} SELECT {IMG} FROM nrm")
def a12_normal_op(spark: SparkSession, sf_dir: str) -> DataFrame:
    return image_out(encode.normal(fx.truth(spark), fx.N, encode.normal_kernel(fx.mask(spark), fx.basis(spark))))


@query(
    f"""WITH RECURSIVE {fx.SQL_SCAN},
low AS (SELECT ku, kv, 0 AS comp, avg(re) AS re, avg(im) AS im FROM ksp WHERE least(ku, 8 - ku) <= 2 AND least(kv, 8 - kv) <= 2 GROUP BY ALL), {fx.sql_inverse('low', 'lo')},
two AS (SELECT 0 AS coil, row, col, re, im FROM lo UNION ALL SELECT 1, row, col, 2 * re, 2 * im FROM lo),
s AS (SELECT *, sqrt(sum(re * re + im * im) OVER (PARTITION BY row, col)) AS tot FROM two)
SELECT coil, row, col, {q6('re / nullif(tot, 0)', 're')}, {q6('im / nullif(tot, 0)', 'im')} FROM s"""
)
def a13_coil_maps(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = fx.samples(spark)
    two = s.unionByName(s.select("slice_id", F.lit(1).alias("coil"), "t", "ku", "kv", (2 * F.col("re")).alias("re"), (2 * F.col("im")).alias("im")))
    return encode.coil_maps(two, fx.N, 4).select("coil", "row", "col", *r6("re", "im"))


def _fidelity(spark: SparkSession) -> DataFrame:
    f = encode.forward(fx.truth(spark), fx.N, fx.mask(spark), fx.basis(spark))
    d = stepsize.difference(fx.samples(spark), f, ["slice_id", "coil", "t", "ku", "kv"])
    return d.agg(F.sum(F.col("re") ** 2 + F.col("im") ** 2).alias("fidelity"))


_FID = f"{fx.SQL_SCAN}, {fx.SQL_TRUTH}, {_FORWARD}, fid AS (SELECT sum(power(k.re - f.re, 2) + power(k.im - f.im, 2)) AS fidelity FROM ksp k JOIN fwd f USING (t, ku, kv))"
_TV = "tvn AS (SELECT sum(sqrt(power(coalesce(d.re - o.re, 0), 2) + power(coalesce(r.re - o.re, 0), 2))) AS tv FROM img o LEFT JOIN img d ON d.row = o.row + 1 AND d.col = o.col AND d.comp = o.comp LEFT JOIN img r ON r.col = o.col + 1 AND r.row = o.row AND r.comp = o.comp)"


@query(f"WITH RECURSIVE {_FID} SELECT {q6('fidelity', 'fidelity')} FROM fid")
def a14_fidelity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _fidelity(spark).select(*r6("fidelity"))


@query(f"WITH RECURSIVE {_FID}, {_TV} SELECT {q6('fidelity + 0.01 * tv', 'objective')} FROM fid, tvn")
def a15_objective(spark: SparkSession, sf_dir: str) -> DataFrame:
    total = spatial.tv(fx.truth(spark)).agg(F.sum("tv").alias("tv"))
    return _fidelity(spark).crossJoin(total).select((F.col("fidelity") + 0.01 * F.col("tv")).alias("objective")).select(*r6("objective"))


def _points(spark: SparkSession) -> DataFrame:
    return sequence.spiral(spark, 3, fx.N, 10, fx.INNER, fx.OUTER)


@query()
def a16_nufft_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    img, p = fx.truth(spark), _points(spark)
    exact, fast = encode.ndft(img, p, fx.N), encode.degrid(img, p, fx.N)
    keys = ["slice_id", "comp", "t", "sample_no"]
    d = stepsize.difference(fast, exact, keys).agg(F.sqrt(F.sum(F.col("re") ** 2 + F.col("im") ** 2)).alias("d"))
    e = exact.agg(F.sqrt(F.sum(F.col("re") ** 2 + F.col("im") ** 2)).alias("e"))
    return d.crossJoin(e).select((F.col("d") / F.col("e")).alias("relative_error"))


@query(
    f"""WITH RECURSIVE {fx.SQL_SCAN}, {fx.SQL_TRUTH},
a3 AS (SELECT t::INTEGER AS t, s::INTEGER AS sample_no, sqrt((s + 0.5) / 10.0::DOUBLE) * {fx._LAST!r}::DOUBLE AS wind, radians((t * 82.5) % 360) AS a FROM range(3) x(t), range(10) y(s)),
p3 AS (SELECT t, sample_no, {fx.INNER / (2 * 3.141592653589793 * fx._GROW)!r}::DOUBLE * (exp({fx._GROW!r}::DOUBLE * wind) - 1) * cos(wind + a) AS kx, {fx.INNER / (2 * 3.141592653589793 * fx._GROW)!r}::DOUBLE * (exp({fx._GROW!r}::DOUBLE * wind) - 1) * sin(wind + a) AS ky FROM a3),
n3 AS (SELECT comp, t, sample_no, sum(re * cos(2 * pi() * (row * kx + col * ky) / 8)) / 8 AS re, -sum(re * sin(2 * pi() * (row * kx + col * ky) / 8)) / 8 AS im FROM img, p3 GROUP BY ALL)
SELECT comp, t, sample_no, round(re, 3) + 0.0 AS re, round(im, 3) + 0.0 AS im FROM n3"""
)
def a16_nufft_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Samples by the gridding window, at the precision it has, against the exact sums."""
    fast = encode.degrid(fx.truth(spark), _points(spark), fx.N)
    return fast.select("comp", "t", "sample_no", *[(F.round(c, 3) + F.lit(0.0)).alias(c) for c in ("re", "im")])


@query(
    f"""WITH RECURSIVE {fx.SQL_SCAN}, {fx.SQL_TRUTH},
a3 AS (SELECT t::INTEGER AS t, s::INTEGER AS sample_no, sqrt((s + 0.5) / 10.0::DOUBLE) * {fx._LAST!r}::DOUBLE AS wind, radians((t * 82.5) % 360) AS a FROM range(3) x(t), range(10) y(s)),
p3 AS (SELECT t, sample_no, {fx.INNER / (2 * 3.141592653589793 * fx._GROW)!r}::DOUBLE * (exp({fx._GROW!r}::DOUBLE * wind) - 1) * cos(wind + a) AS kx, {fx.INNER / (2 * 3.141592653589793 * fx._GROW)!r}::DOUBLE * (exp({fx._GROW!r}::DOUBLE * wind) - 1) * sin(wind + a) AS ky FROM a3),
n3 AS (SELECT comp, t, sample_no, sum(re * cos(2 * pi() * (row * kx + col * ky) / 8)) / 8 AS re, -sum(re * sin(2 * pi() * (row * kx + col * ky) / 8)) / 8 AS im FROM img, p3 GROUP BY ALL)
SELECT comp, t, sample_no, {q6('re', 're')}, {q6('im', 'im')} FROM n3"""
)
def a17_ndft(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode.ndft(fx.truth(spark), _points(spark), fx.N).select("comp", "t", "sample_no", *r6("re", "im"))


# --- spatial operators on the compressed phantom -------------------------------------

_IMG = f"WITH RECURSIVE {fx.SQL_SCAN}, {fx.SQL_TRUTH}"
_NEXT = "LEFT JOIN img d ON d.row = o.row + 1 AND d.col = o.col AND d.comp = o.comp LEFT JOIN img r ON r.col = o.col + 1 AND r.row = o.row AND r.comp = o.comp"


@query(f"{_IMG} SELECT o.comp, {q6('sum(sqrt(power(coalesce(d.re - o.re, 0), 2) + power(coalesce(r.re - o.re, 0), 2)))', 'tv')} FROM img o {_NEXT} GROUP BY o.comp")
def a40_tv_norm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spatial.tv(fx.truth(spark)).select("comp", *r6("tv"))


@query(f"{_IMG} SELECT o.row, o.col, o.comp, {q6('coalesce(d.re - o.re, 0)', 'dre_r')}, {q6('coalesce(r.re - o.re, 0)', 'dre_c')} FROM img o {_NEXT}")
def a41_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spatial.grad(fx.truth(spark)).select("row", "col", "comp", *r6("dre_r", "dre_c"))


@query(
    f"""{_IMG}, g AS (SELECT o.row, o.col, o.comp, coalesce(d.re - o.re, 0) AS a, coalesce(r.re - o.re, 0) AS b FROM img o {_NEXT})
SELECT o.row, o.col, o.comp, {q6('CASE WHEN o.row < 7 THEN o.a ELSE 0 END - coalesce(u.a, 0) + CASE WHEN o.col < 7 THEN o.b ELSE 0 END - coalesce(l.b, 0)', 'dre')}
FROM g o LEFT JOIN g u ON u.row = o.row - 1 AND u.col = o.col AND u.comp = o.comp LEFT JOIN g l ON l.col = o.col - 1 AND l.row = o.row AND l.comp = o.comp"""
)
def a42_divergence(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = spatial.grad(fx.truth(spark)).withColumnsRenamed({"dre_r": "pr_r", "dim_r": "pi_r", "dre_c": "pr_c", "dim_c": "pi_c"})
    return spatial.div(g).select("row", "col", "comp", *r6("dre"))


@query(f"{_IMG}, {fx.sql_prox('img', 'px', '0.3', 2)} SELECT {IMG} FROM px")
def a43_tv_prox2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return image_out(spatial.tv_prox(fx.truth(spark), 0.3, 2))


@query(f"{_IMG}, g AS (SELECT o.row, o.col, sqrt(sum(power(coalesce(d.re - o.re, 0), 2) + power(coalesce(r.re - o.re, 0), 2))) AS v FROM img o {_NEXT} GROUP BY o.row, o.col) SELECT {q6('sum(v)', 'tv')} FROM g")
def a44_tv_joint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spatial.tv(fx.truth(spark), joint=True).select(*r6("tv"))


_SOFT = "(sign({0}) * greatest(abs({0}) - 0.1, 0))"
_HAAR = ["(sum(re * a) OVER b / 2)", "(sum(re * c) OVER b / 2)", "(sum(re * a * c) OVER b / 2)"]


@query(
    f"""{_IMG}, m AS (SELECT row, col, comp, re, sr, sc, (row + sr) % 8 AS r, (col + sc) % 8 AS q FROM img, range(2) x(sr), range(2) y(sc)),
s AS (SELECT *, CASE WHEN r % 2 = 0 THEN 1 ELSE -1 END AS a, CASE WHEN q % 2 = 0 THEN 1 ELSE -1 END AS c FROM m),
v AS (SELECT row, col, comp, sum(re) OVER b / 4 + (a * {_SOFT.format(_HAAR[0])} + c * {_SOFT.format(_HAAR[1])} + a * c * {_SOFT.format(_HAAR[2])}) / 2 AS re FROM s WINDOW b AS (PARTITION BY comp, sr, sc, r // 2, q // 2))
SELECT row, col, comp, {q6('avg(re)', 're')} FROM v GROUP BY row, col, comp"""
)
def a45_cycle_spin1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spatial.cycle_spin(fx.truth(spark), fx.N, 0.1).select("row", "col", "comp", *r6("re"))


@query(
    f"""{_IMG}, sp AS (SELECT u.ku::INTEGER AS ku, v.kv::INTEGER AS kv, comp, sum(re * cos(2 * pi() * (row * u.ku + col * v.kv) / 8)) / 8 AS re, -sum(re * sin(2 * pi() * (row * u.ku + col * v.kv) / 8)) / 8 AS im FROM img, range(8) u(ku), range(8) v(kv) GROUP BY ALL),
cut AS (SELECT * FROM sp WHERE power(least(ku, 8 - ku), 2) + power(least(kv, 8 - kv), 2) <= 6.25), {fx.sql_inverse('cut', 'lp')} SELECT row, col, comp, {q6('re', 're')} FROM lp"""
)
def a46_low_pass(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spatial.low_pass(fx.truth(spark), fx.N, 2.5).select("row", "col", "comp", *r6("re"))


# --- step sizes and iterations ----------------------------------------------------------

_PROBLEM = f"WITH RECURSIVE {fx.SQL_SCAN}, {fx.sql_grid()}, {fx.SQL_ATOMS}, {fx.SQL_KERNEL}, {fx.sql_adjoint('b')}"
_SAMPLE_KEYS = ["slice_id", "coil", "t", "ku", "kv"]


@query(f"WITH RECURSIVE {fx.SQL_SCAN}, {fx.SQL_TRUTH}, {_FORWARD} SELECT {q6('sum(k.re * f.re + k.im * f.im) / sum(f.re * f.re + f.im * f.im)', 'step')} FROM ksp k JOIN fwd f USING (t, ku, kv)")
def a50_rescale(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = encode.forward(fx.truth(spark), fx.N, fx.mask(spark), fx.basis(spark))
    return stepsize.rescale(fx.samples(spark), f, _SAMPLE_KEYS).select(*r6("step"))


@query(
    f"""{_PROBLEM}, {fx.SQL_TRUTH}, {fx.sql_combine('dl', img='1.0', b='-1.0')}, {fx.sql_normal('dl', 'nd')}
SELECT {q6('0.99 * (SELECT sum(re * re + im * im) FROM dl) / (SELECT sum(re * re + im * im) FROM nd)', 'bound')}, 0.5 <= 0.99 * (SELECT sum(re * re + im * im) FROM dl) / (SELECT sum(re * re + im * im) FROM nd) AS passes"""
)
def a53_cond_a(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = fx.problem(spark)
    d = relational.combine(fx.truth(spark), 1.0, p.b, -1.0)
    return stepsize.cond_a(d, p.normal(d), 0.5).select(*r6("bound"), "passes")


@query(
    f"""{_PROBLEM}, {fx.SQL_TRUTH}, {fx.sql_normal('img', 'nt')}, {fx.sql_combine('rs', b='1.0', nt='-1.0')}
SELECT {q6('(SELECT sum(re * re + im * im) FROM b)', 'before')}, {q6('(SELECT sum(re * re + im * im) FROM rs)', 'after')}, (SELECT sum(re * re + im * im) FROM rs) <= (SELECT sum(re * re + im * im) FROM b) AS passes"""
)
def a54_cond_b(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = fx.problem(spark)
    after = relational.combine(p.b, 1.0, p.normal(fx.truth(spark)), -1.0)
    return stepsize.cond_b(p.b, after).select(*r6("before", "after"), "passes")


@query(f"WITH {fx.SQL_MASK}, c AS (SELECT t, count(*) AS m FROM mask GROUP BY t) SELECT {q6('64.0::DOUBLE / avg(m)', 'step')} FROM c")
def a55_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = fx.mask(spark).select(F.lit(0).alias("slice_id"), F.lit(0).alias("coil"), "t", "ku", "kv")
    return stepsize.undersampling_ratio(s, fx.N).select(*r6("step"))


_CFG = EngineConfig(lam=0.2, tv_iters=2)
_STEP = 0.5


def _sql_grad(u: str, out: str, step: float) -> str:
    return f"{fx.sql_normal(u, out + '_n')}, {fx.sql_combine(out, **{u: '1.0', out + '_n': f'-{step}', 'b': f'{step}'})}"


_SEQ1 = f"{_PROBLEM}, z0 AS (SELECT row, col, comp, {_STEP} * re AS re, {_STEP} * im AS im FROM b), {fx.sql_match('z0', 'm0')}, {fx.sql_prox('m0', 'u1', str(_STEP * 0.2), 2)}"
_SEQ2 = f"{_SEQ1}, {_sql_grad('u1', 'z1', _STEP)}, {fx.sql_match('z1', 'm1')}, {fx.sql_prox('m1', 'u2', str(_STEP * 0.2), 2)}"


@query(f"{_SEQ1} SELECT {IMG} FROM u1")
def a60_seq_iter1(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = fx.problem(spark)
    return image_out(relational.sequential_step(p.b, p, _STEP, _CFG, True, first=True))


@query(f"{_SEQ2} SELECT {IMG} FROM u2")
def a60_seq_iter2(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = fx.problem(spark)
    u = relational.cut(relational.sequential_step(p.b, p, _STEP, _CFG, True, first=True))
    return image_out(relational.sequential_step(u, p, _STEP, _CFG, True))


_PAR1 = f"{_PROBLEM}, z0 AS (SELECT row, col, comp, {_STEP} * re AS re, {_STEP} * im AS im FROM b), {fx.sql_match('z0', 'zb1')}, {fx.sql_prox('z0', 'zs1', str(_STEP * 0.2), 2)}, {fx.sql_combine('u1', zb1='0.5', zs1='0.5')}"
_PAR2 = (
    f"{_PAR1}, {_sql_grad('u1', 'g1', _STEP)}, {fx.sql_combine('ob', u1='1.0', zb1='-1.0')}, {fx.sql_combine('os', u1='1.0', zs1='-1.0')}, {fx.sql_combine('pb', g1='1.0', ob='1.0')}, {fx.sql_combine('ps', g1='1.0', os='1.0')}, "
    f"{fx.sql_match('pb', 'qb')}, {fx.sql_prox('ps', 'qs', str(_STEP * 0.2), 2)}, {fx.sql_combine('u2', qb='0.5', ob='-0.5', qs='0.5', os='-0.5')}"
)


@query(f"{_PAR1} SELECT {IMG} FROM u1")
def a61_par_iter1(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = fx.problem(spark)
    z = relational.cut(relational.zero(p.b))
    return image_out(relational.parallel_step((z, z, z), p, _STEP, _CFG)[0])


@query(f"{_PAR2} SELECT {IMG} FROM u2")
def a61_par_iter2(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = fx.problem(spark)
    p.b, p.kernel, p.atoms = (relational.cut(d) for d in (p.b, p.kernel, p.atoms))
    z = relational.cut(relational.zero(p.b))
    state = tuple(relational.cut(d) for d in relational.parallel_step((z, z, z), p, _STEP, _CFG))
    return image_out(relational.parallel_step(state, p, _STEP, _CFG)[0])


_ROWS = "(0, 0, 5.0, true), (1, 0, 9.0, false), (1, 1, 3.0, true), (2, 0, 3.5, true), (3, 0, 3.0, true)"


@query(f"WITH h(iter, attempt, fidelity, accepted) AS (VALUES {_ROWS}) SELECT arg_min(iter, (fidelity, iter)) FILTER (accepted) AS iter, min(fidelity) FILTER (accepted)::DOUBLE AS fidelity, count(*) AS attempts FROM h")
def a63_best_iterate(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [(0, 0, 5.0, True), (1, 0, 9.0, False), (1, 1, 3.0, True), (2, 0, 3.5, True), (3, 0, 3.0, True)]
    h = spark.createDataFrame([(0, *r) for r in rows], "slice_id int, iter int, attempt int, fidelity double, accepted boolean")
    return metrics.best_iterate(h, ["slice_id"]).select("iter", "fidelity", "attempts")


@query("WITH s(comp, value) AS (VALUES (0, 9.0), (1, 4.0), (2, 2.0), (3, 1.0)) SELECT comp, sum(value) OVER (ORDER BY comp)::DOUBLE AS energy, round((sum(value) OVER (ORDER BY comp) / sum(value) OVER ())::DOUBLE, 6) AS share FROM s")
def c9_rank_energy(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = spark.createDataFrame([(0, 9.0), (1, 4.0), (2, 2.0), (3, 1.0)], "comp int, value double")
    return rank_energy(v).select("comp", "energy", F.round("share", 6).alias("share"))


# --- the first baseline and the measures on its maps ------------------------------------

_ZERO = f"{_PROBLEM}, {fx.sql_match('b', 'zf')}, maps AS (SELECT row, col, atom_id, g.t1, g.t2, rho FROM zf_m JOIN grid g USING (atom_id))"


def _zero_fill(spark: SparkSession) -> DataFrame:
    p = fx.problem(spark)
    maps = relational.match_image(p.b, p.atoms)[1]
    return maps.join(F.broadcast(p.atoms.select(F.col("id").alias("atom_id"), "t1", "t2")), "atom_id")


@query(f"{_ZERO} SELECT row, col, atom_id::BIGINT AS atom_id, t1, t2, {q6('rho', 'rho')} FROM maps")
def b1_zero_fill(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _zero_fill(spark).select("row", "col", "atom_id", "t1", "t2", *r6("rho"))


@query(f"{_PROBLEM}, z0 AS (SELECT row, col, comp, 0.5 * re AS re, 0.5 * im AS im FROM b), {fx.sql_match('z0', 'u1')}, {_sql_grad('u1', 'z1', 0.5)}, {fx.sql_match('z1', 'u2')} SELECT {IMG} FROM u2")
def b2_proj_grad_iter2(spark: SparkSession, sf_dir: str) -> DataFrame:
    p, plain = fx.problem(spark), EngineConfig(lam=0.0)
    u = relational.cut(relational.sequential_step(p.b, p, 0.5, plain, True, first=True))
    return image_out(relational.sequential_step(u, p, 0.5, plain, True))


@query(
    f"""WITH RECURSIVE {fx.SQL_SCAN}, one AS (SELECT * FROM basis WHERE comp = 0),
cells AS (SELECT ku, kv, sum(sqrt(w) * re * b) AS re, sum(sqrt(w) * im * b) AS im, sum(w * b * b) AS k FROM ksp JOIN one USING (t) GROUP BY ALL),
sol AS (SELECT ku, kv, 0 AS comp, re / (k * 1.01) AS re, im / (k * 1.01) AS im FROM cells), {fx.sql_inverse('sol', 'tm')} SELECT {IMG} FROM tm"""
)
def b3_time_mix_r1(spark: SparkSession, sf_dir: str) -> DataFrame:
    b, m = fx.basis(spark).filter("comp = 0"), fx.mask(spark)
    cells = encode.collect_cells(fx.samples(spark), m, b)
    k = encode.normal_kernel(m, b).select("ku", "kv", F.col("re").alias("k"))
    sol = cells.join(k, ["ku", "kv"]).select("slice_id", "ku", "kv", "comp", (F.col("re") / (1.01 * F.col("k"))).alias("re"), (F.col("im") / (1.01 * F.col("k"))).alias("im"))
    return image_out(encode.image(sol, fx.N, ["slice_id", "comp"]))


_TRUTH = "FROM maps m JOIN ph USING (row, col) WHERE mask"


@query(f"{_ZERO} SELECT {q6('avg(abs(m.t1 - ph.t1) / ph.t1)', 'err_t1')}, {q6('avg(abs(m.t2 - ph.t2) / ph.t2)', 'err_t2')} {_TRUTH}")
def c1_rel_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.rel_error(_zero_fill(spark), phantom.digital(spark, fx.N), ["slice_id"]).select(*r6("err_t1", "err_t2"))


@query(f"{_ZERO} SELECT {q6('avg(m.rho / ph.pd)', 'pd_ratio')} {_TRUTH}")
def c8_pd_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.pd_ratio(_zero_fill(spark), phantom.digital(spark, fx.N), ["slice_id"]).select(*r6("pd_ratio"))


_REF = f"{_ZERO}, b2 AS (SELECT * FROM b), {_sql_grad('b2', 'z1', 0.5)}, {fx.sql_match('z1', 'rf')}, ref AS (SELECT row, col, g.t1, g.t2 FROM rf_m JOIN grid g USING (atom_id))"


@query(f"{_REF} SELECT {q6('avg(abs(m.t1 - r.t1) / r.t1)', 'diff_t1')}, {q6('avg(abs(m.t2 - r.t2) / r.t2)', 'diff_t2')} FROM maps m JOIN ref r USING (row, col)")
def c7_ref_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = fx.problem(spark)
    later = relational.match_image(relational.gradient_point(p.b, p, 0.5), p.atoms)[1]
    ref = later.join(F.broadcast(p.atoms.select(F.col("id").alias("atom_id"), "t1", "t2")), "atom_id")
    return metrics.vs_reference(_zero_fill(spark), ref, ["slice_id"]).select(*r6("diff_t1", "diff_t2"))


_DISCS = """px AS (SELECT (i // 8)::INTEGER AS row, (i % 8)::INTEGER AS col FROM range(64) r(i)),
rois AS (SELECT row, col, n_nationkey, n_regionkey AS roi_id FROM px JOIN nation ON n_nationkey // 5 = floor((row + 0.5) / 1.6) AND n_nationkey % 5 = floor((col + 0.5) / 1.6)
  WHERE sqrt(power(row + 0.5 - (n_nationkey // 5 + 0.5) * 1.6, 2) + power(col + 0.5 - (n_nationkey % 5 + 0.5) * 1.6, 2)) < 0.38 * 1.6)"""


@query(
    f"""{_ZERO}, {_DISCS}, d AS (SELECT roi_id, n_nationkey, avg(t1) AS m1, stddev_pop(t1) AS s1, avg(t2) AS m2, stddev_pop(t2) AS s2 FROM maps JOIN rois USING (row, col) GROUP BY ALL)
SELECT roi_id, {q6('avg(m1)', 'mean_t1')}, {q6('avg(m2)', 'mean_t2')}, {q6('avg(s1 / m1)', 'spread_t1')}, {q6('avg(s2 / m2)', 'spread_t2')} FROM d GROUP BY roi_id"""
)
def c2_roi_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    rois = phantom.inserts(spark, read(spark, sf_dir, "nation"), fx.N)
    return metrics.roi(_zero_fill(spark), rois, ["slice_id"]).select("roi_id", *r6("mean_t1", "mean_t2", "spread_t1", "spread_t2"))


@query(
    f"""{_ZERO}, {_DISCS}, m AS (SELECT * FROM maps JOIN rois USING (row, col)),
g AS (SELECT roi_id, coalesce(lead(t1) OVER (PARTITION BY n_nationkey, col ORDER BY row) - t1, 0) AS a, coalesce(lead(t1) OVER (PARTITION BY n_nationkey, row ORDER BY col) - t1, 0) AS b FROM m)
SELECT roi_id, {q6('sum(sqrt(a * a + b * b))', 'ringing')} FROM g GROUP BY roi_id"""
)
def c12_ringing(spark: SparkSession, sf_dir: str) -> DataFrame:
    rois = phantom.inserts(spark, read(spark, sf_dir, "nation"), fx.N)
    return metrics.ringing(_zero_fill(spark), rois, ["slice_id"]).select("roi_id", *r6("ringing"))


@query("SELECT 256 AS n, 10 AS rank, 1000 AS length, (256 * 256 * 10)::BIGINT AS own_values, (1000::BIGINT * 2000 * 48) AS mixed_values, 655360 * 8 / 1e6::DOUBLE AS own_mb, 96000000 * 8.0::DOUBLE / 1e6 AS mixed_mb")
def c5_working_set(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.working_set_table(spark.createDataFrame([(256, 10, 1000, 2000, 48)], "n int, rank int, length int, samples int, interleaves int"))


@query("WITH e(length, method, e1, e2) AS (VALUES (60, 'par_bt', 0.02, 0.04), (60, 'base_zero_fill', 0.05, 0.1), (80, 'par_bt', 0.01, 0.02), (80, 'base_zero_fill', 0.04, 0.05)) SELECT a.length, a.method, round((a.e1 / b.e1)::DOUBLE, 6) AS gain_t1, round((a.e2 / b.e2)::DOUBLE, 6) AS gain_t2 FROM e a JOIN e b ON a.length = b.length AND b.method = 'par_bt' WHERE a.method <> 'par_bt'")
def c11_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = spark.createDataFrame([(60, "par_bt", 0.02, 0.04), (60, "base_zero_fill", 0.05, 0.1), (80, "par_bt", 0.01, 0.02), (80, "base_zero_fill", 0.04, 0.05)], "length int, method string, err_t1 double, err_t2 double")
    return metrics.gain(e, ["length"]).select("length", "method", F.round("gain_t1", 6).alias("gain_t1"), F.round("gain_t2", 6).alias("gain_t2"))
