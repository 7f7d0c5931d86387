"""The 8 x 8 scan of the oracle queries, as DataFrames and as SQL.

The SQL side is worded on its own: a recursive sum for signals, direct double
sums for transforms. Twelve time points, a cosine basis of two components.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import dictionary, encode, phantom, sequence
from ..operators.phantom import CLASSES, ELLIPSES
from ..plans.relational import Problem

N, L, R, SAMPLES, INNER, OUTER, EVERY = 8, 12, 2, 40, 1.5, 3.0, 200


def basis(spark: SparkSession) -> DataFrame:
    t, j = F.col("t"), F.col("comp")
    grid = spark.range(L).select(F.col("id").cast("int").alias("t")).crossJoin(spark.range(R).select(F.col("id").cast("int").alias("comp")))
    value = F.cos(math.pi * (t + 0.5) * (j + 1) / L) * math.sqrt(2 / L)
    return grid.select("t", "comp", value.alias("re"), F.lit(0.0).alias("im"))


def mask(spark: SparkSession) -> DataFrame:
    return sequence.sampling_mask(sequence.spiral(spark, L, N, SAMPLES, INNER, OUTER), N)


def class_signals(spark: SparkSession) -> DataFrame:
    """class, t, v."""
    classes = phantom.class_table(spark)
    out = dictionary.simulate_fold(classes.select("class", "t1", "t2"), sequence.pulse_schedule(spark, L))
    return out.select("class", F.posexplode("sig").alias("t", "v"))


def truth(spark: SparkSession) -> DataFrame:
    """slice_id, row, col, comp, re, im: the compressed phantom."""
    p = phantom.digital(spark, N).select("row", "col", "class", "pd").filter("class is not null")
    x = p.join(F.broadcast(class_signals(spark)), "class").join(F.broadcast(basis(spark)), "t")
    x = x.groupBy("row", "col", "comp").agg(F.sum(F.col("pd") * F.col("v") * F.col("re")).alias("re"))
    full = phantom.pixels(spark, N).crossJoin(spark.range(R).select(F.col("id").cast("int").alias("comp")))
    return full.join(x, ["row", "col", "comp"], "left").select(
        F.lit(0).cast("long").alias("slice_id"), "row", "col", "comp", F.coalesce("re", F.lit(0.0)).alias("re"), F.lit(0.0).alias("im")
    )


def samples(spark: SparkSession) -> DataFrame:
    """slice_id, coil, t, ku, kv, re, im of the full phantom, sqrt(w) included."""
    p = phantom.digital(spark, N).filter("class is not null").select("class", "row", "col", F.col("pd").alias("re"), F.lit(0.0).alias("im"))
    spec = encode.spectrum(p, N, ["class"])
    x = mask(spark).join(spec, ["ku", "kv"]).join(F.broadcast(class_signals(spark)), ["class", "t"])
    x = x.groupBy("t", "ku", "kv").agg((F.sum(F.col("re") * F.col("v")) * F.sqrt(F.first("w"))).alias("re"), (F.sum(F.col("im") * F.col("v")) * F.sqrt(F.first("w"))).alias("im"))
    return x.select(F.lit(0).cast("long").alias("slice_id"), F.lit(0).alias("coil"), "t", "ku", "kv", "re", "im")


def atoms(spark: SparkSession) -> DataFrame:
    """id, x (interleaved), norm, t1, t2: every 200th atom of the grid."""
    params = dictionary.param_grid(spark).filter(F.col("atom_id") % EVERY == 0)
    sig = dictionary.simulate_fold(params, sequence.pulse_schedule(spark, L)).select("atom_id", "t1", "t2", F.posexplode("sig").alias("t", "v"))
    x = sig.join(F.broadcast(basis(spark)), "t").groupBy("atom_id", "t1", "t2", "comp").agg(F.sum(F.col("v") * F.col("re")).alias("c"))
    x = x.groupBy("atom_id", "t1", "t2").agg(F.sort_array(F.collect_list(F.struct("comp", "c"))).alias("p"))
    x = x.select(F.col("atom_id").cast("long").alias("id"), "t1", "t2", F.flatten(F.transform("p", lambda v: F.array(v["c"], F.lit(0.0)))).alias("x"))
    return x.withColumn("norm", F.sqrt(F.aggregate(F.transform("x", lambda v: v * v), F.lit(0.0), lambda s, v: s + v)))


def problem(spark: SparkSession) -> Problem:
    m, b = mask(spark), basis(spark)
    return Problem(N, encode.adjoint(samples(spark), N, m, b), encode.normal_kernel(m, b), atoms(spark))


_EDGE = N / 2 - 0.5
_GROW = (OUTER - INNER) / _EDGE / (2 * math.pi)
_LAST = math.log(1 + _GROW * _EDGE * 2 * math.pi / INNER) / _GROW
_ELLIPSE = " ".join(f"WHEN power((x - ({cx})) / {ax}, 2) + power((y - ({cy})) / {ay}, 2) <= 1 THEN {c}" for c, cx, cy, ax, ay in reversed(ELLIPSES))


def sql_phantom(n: int, name: str = "ph") -> str:
    return f"""cls(class, t1, t2, pd) AS (VALUES {', '.join(f'({c}, {a}::DOUBLE, {b}::DOUBLE, {p}::DOUBLE)' for c, a, b, p in CLASSES)}),
{name}_xy AS (SELECT (i // {n})::INTEGER AS row, (i % {n})::INTEGER AS col, ((i % {n}) + 0.5) * 2.0 / {n} - 1 AS x, ((i // {n}) + 0.5) * 2.0 / {n} - 1 AS y FROM range({n * n}) r(i)),
{name}_k AS (SELECT row, col, (CASE {_ELLIPSE} END)::INTEGER AS class FROM {name}_xy),
{name} AS (SELECT row, col, class, coalesce(t1, 0) AS t1, coalesce(t2, 0) AS t2, coalesce(pd, 0) AS pd, class IS NOT NULL AS mask FROM {name}_k LEFT JOIN cls USING (class))"""


def sql_schedule(length: int = L) -> str:
    return f"""sched AS (SELECT i::INTEGER AS t, 13.55 + 1.45 * sin(2 * pi() * i / 37) AS tr, 74 * (0.3 + 0.7 * abs(sin(1.7 * (i // 25) + 0.6))) * sin(pi() * (i % 25) / 25) AS fa FROM range({length}) r(i))"""


def sql_signal(params: str, key: str, name: str, model: str = "coherent") -> str:
    """Recursive CTE: key, t, v over the rows of ``params`` (key, t1, t2)."""
    x, m = f"{name}_r.x * cos(radians(fa)) + {name}_r.m * sin(radians(fa))", f"{name}_r.m * cos(radians(fa)) - {name}_r.x * sin(radians(fa))"
    if model == "spoiled":
        x, m = f"{name}_r.m * sin(radians(fa))", f"{name}_r.m * cos(radians(fa))"
    keep = "0.0::DOUBLE" if model == "spoiled" else f"({x}) * exp(-tr / t2)"
    return f"""{name}_r(k, t1, t2, t, x, m, v) AS (
SELECT {key}, t1, t2, -1, 0.0::DOUBLE, 1 - 2 * exp(-21 / t1), 0.0::DOUBLE FROM {params}
UNION ALL SELECT k, t1, t2, s.t, {keep}, 1 + (({m}) - 1) * exp(-tr / t1), ({x}) * exp(-2 / t2) FROM {name}_r JOIN sched s ON s.t = {name}_r.t + 1),
{name} AS (SELECT k AS {key}, t, v FROM {name}_r WHERE t >= 0)"""


def sql_grid() -> str:
    axis = lambda ranges, c: f"SELECT DISTINCT v::DOUBLE AS {c} FROM (" + " UNION ALL ".join(f"SELECT * FROM range({a}, {z + 1}, {s}) r(v)" for a, z, s in ranges) + ")"
    return f"grid AS (SELECT (row_number() OVER (ORDER BY t1, t2) - 1)::INTEGER AS atom_id, t1, t2 FROM ({axis(dictionary.T1_RANGES, 't1')}) a JOIN ({axis(dictionary.T2_RANGES, 't2')}) b ON t1 >= t2)"


SQL_BASIS = f"basis AS (SELECT t::INTEGER AS t, j::INTEGER AS comp, cos(pi() * (t + 0.5) * (j + 1) / {L}) * sqrt(2.0::DOUBLE / {L}) AS b FROM range({L}) a(t), range({R}) c(j))"
SQL_MASK = f"""ang AS (SELECT t, ((t - t // 48) * 82.5 + (t // 48) * 84.0) % 360.0 AS angle FROM range({L}) r(t)),
pts AS (SELECT t, sqrt((s + 0.5) / {SAMPLES}.0::DOUBLE) * {_LAST!r}::DOUBLE AS wind, radians(angle) AS a FROM ang, range({SAMPLES}) r(s)),
pos AS (SELECT t, {INNER / (2 * math.pi * _GROW)!r}::DOUBLE * (exp({_GROW!r}::DOUBLE * wind) - 1) AS rad, wind + a AS turn FROM pts),
hits AS (SELECT DISTINCT t::INTEGER AS t, (((round(rad * cos(turn))::INTEGER % {N}) + {N}) % {N}) AS ku, (((round(rad * sin(turn))::INTEGER % {N}) + {N}) % {N}) AS kv FROM pos),
mask AS (SELECT t, ku, kv, {L}.0::DOUBLE / count(*) OVER (PARTITION BY ku, kv) AS w FROM hits)"""
SQL_SAMPLES = f"""spec AS (SELECT class, u.ku::INTEGER AS ku, v.kv::INTEGER AS kv, sum(pd * cos(2 * pi() * (row * u.ku + col * v.kv) / {N})) / {N} AS re, -sum(pd * sin(2 * pi() * (row * u.ku + col * v.kv) / {N})) / {N} AS im
  FROM ph, range({N}) u(ku), range({N}) v(kv) WHERE class IS NOT NULL GROUP BY ALL),
ksp AS (SELECT m.t, m.ku, m.kv, sqrt(any_value(w)) * sum(re * v) AS re, sqrt(any_value(w)) * sum(im * v) AS im, any_value(w) AS w
  FROM mask m JOIN spec s ON s.ku = m.ku AND s.kv = m.kv JOIN csig c ON c.class = s.class AND c.t = m.t GROUP BY ALL)"""
#: Everything up to the samples.
SQL_SCAN = ",\n".join([sql_phantom(N), sql_schedule(), sql_signal("cls", "class", "csig"), SQL_BASIS, SQL_MASK, SQL_SAMPLES])
SQL_TRUTH = f"""img AS (SELECT row, col, b.comp, coalesce(sum(pd * v * b), 0) AS re, 0.0::DOUBLE AS im FROM ph CROSS JOIN basis b LEFT JOIN csig c ON c.class = ph.class AND c.t = b.t GROUP BY ALL)"""
SQL_ATOMS = f"""pick AS (SELECT atom_id, t1, t2 FROM grid WHERE atom_id % {EVERY} = 0),
{sql_signal('pick', 'atom_id', 'asig')},
atoms AS (SELECT atom_id, comp, sum(v * b) AS c FROM asig JOIN basis USING (t) GROUP BY ALL),
norms AS (SELECT atom_id, sqrt(sum(c * c)) AS norm FROM atoms GROUP BY ALL)"""
SQL_KERNEL = "kern AS (SELECT ku, kv, a.comp AS j, c.comp AS j2, sum(w * a.b * c.b) AS k FROM mask JOIN basis a USING (t) JOIN basis c USING (t) GROUP BY ALL)"


def sql_inverse(cells: str, out: str) -> str:
    """Image (row, col, comp, re, im) of cell values by a direct double sum."""
    angle = f"(2 * pi() * (r.row * ku + c.col * kv) / {N})"
    return f"""{out} AS (SELECT r.row::INTEGER AS row, c.col::INTEGER AS col, comp, sum(re * cos({angle}) - im * sin({angle})) / {N} AS re, sum(re * sin({angle}) + im * cos({angle})) / {N} AS im
  FROM {cells}, range({N}) r(row), range({N}) c(col) GROUP BY ALL)"""


def sql_adjoint(out: str = "adj") -> str:
    return f"{out}_c AS (SELECT ku, kv, comp, sum(sqrt(w) * re * b) AS re, sum(sqrt(w) * im * b) AS im FROM ksp JOIN basis USING (t) GROUP BY ALL),\n" + sql_inverse(f"{out}_c", out)


def sql_normal(src: str, out: str) -> str:
    angle = f"(2 * pi() * (row * u.ku + col * v.kv) / {N})"
    return f"""{out}_s AS (SELECT u.ku::INTEGER AS ku, v.kv::INTEGER AS kv, comp, sum(re * cos({angle}) + im * sin({angle})) / {N} AS re, sum(im * cos({angle}) - re * sin({angle})) / {N} AS im
  FROM {src}, range({N}) u(ku), range({N}) v(kv) GROUP BY ALL),
{out}_k AS (SELECT s.ku, s.kv, j2 AS comp, sum(re * k) AS re, sum(im * k) AS im FROM {out}_s s JOIN kern ON kern.ku = s.ku AND kern.kv = s.kv AND j = comp GROUP BY ALL),
{sql_inverse(f'{out}_k', out)}"""


def sql_match(src: str, out: str) -> str:
    """Image after matching; {out}_m holds row, col, atom_id, rho."""
    return f"""{out}_p AS (SELECT row, col, atom_id, round(sqrt(power(sum(re * c), 2) + power(sum(im * c), 2)) / any_value(norm), 9) AS score, sum(re * c) / power(any_value(norm), 2) AS rho
  FROM {src} JOIN atoms USING (comp) JOIN norms USING (atom_id) GROUP BY row, col, atom_id),
{out}_m AS (SELECT row, col, atom_id, greatest(rho, 0) AS rho FROM {out}_p QUALIFY row_number() OVER (PARTITION BY row, col ORDER BY score DESC, atom_id) = 1),
{out} AS (SELECT row, col, comp, rho * c AS re, 0.0::DOUBLE AS im FROM {out}_m JOIN atoms USING (atom_id))"""


def sql_prox(src: str, out: str, s: str, iters: int) -> str:
    """Dual projection iterations of total variation, by self-joins on neighbours."""
    ctes = [f"{out}_0 AS (SELECT row, col, comp, re AS zr, im AS zi, 0.0::DOUBLE AS ar, 0.0::DOUBLE AS ai, 0.0::DOUBLE AS br, 0.0::DOUBLE AS bi FROM {src})"]

    def divergence(i: int) -> str:
        last = f"CASE WHEN o.row < {N - 1} THEN o.a{{0}} ELSE 0 END - coalesce(u.a{{0}}, 0) + CASE WHEN o.col < {N - 1} THEN o.b{{0}} ELSE 0 END - coalesce(l.b{{0}}, 0)"
        return f"""{out}_d{i} AS (SELECT o.*, {last.format('r')} AS dr, {last.format('i')} AS di FROM {out}_{i} o
  LEFT JOIN {out}_{i} u ON u.row = o.row - 1 AND u.col = o.col AND u.comp = o.comp LEFT JOIN {out}_{i} l ON l.row = o.row AND l.col = o.col - 1 AND l.comp = o.comp)"""

    for i in range(iters):
        ctes.append(divergence(i))
        ctes.append(f"{out}_q{i} AS (SELECT *, dr - zr / ({s}) AS qr, di - zi / ({s}) AS qi FROM {out}_d{i})")
        ctes.append(f"""{out}_g{i} AS (SELECT o.*, coalesce(d.qr - o.qr, 0) AS g1, coalesce(d.qi - o.qi, 0) AS g2, coalesce(r.qr - o.qr, 0) AS g3, coalesce(r.qi - o.qi, 0) AS g4 FROM {out}_q{i} o
  LEFT JOIN {out}_q{i} d ON d.row = o.row + 1 AND d.col = o.col AND d.comp = o.comp LEFT JOIN {out}_q{i} r ON r.row = o.row AND r.col = o.col + 1 AND r.comp = o.comp)""")
        size = "(1 + 0.125 * sqrt(g1 * g1 + g2 * g2 + g3 * g3 + g4 * g4))"
        ctes.append(f"{out}_{i + 1} AS (SELECT row, col, comp, zr, zi, (ar + 0.125 * g1) / {size} AS ar, (ai + 0.125 * g2) / {size} AS ai, (br + 0.125 * g3) / {size} AS br, (bi + 0.125 * g4) / {size} AS bi FROM {out}_g{i})")
    ctes.append(divergence(iters))
    ctes.append(f"{out} AS (SELECT row, col, comp, zr - ({s}) * dr AS re, zi - ({s}) * di AS im FROM {out}_d{iters})")
    return ",\n".join(ctes)


def sql_combine(out: str, **parts: str) -> str:
    """Weighted sum of images: keyword = name of image, value = weight."""
    names = list(parts)
    joins = " ".join(f"JOIN {n} USING (row, col, comp)" for n in names[1:])
    total = lambda c: " + ".join(f"({w}) * {n}.{c}" for n, w in parts.items())
    return f"{out} AS (SELECT {names[0]}.row, {names[0]}.col, {names[0]}.comp, {total('re')} AS re, {total('im')} AS im FROM {names[0]} {joins})"
