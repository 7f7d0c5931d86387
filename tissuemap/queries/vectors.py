"""Queries of subspaces and matching on the given tables."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import grams, matching, subspace
from ..plans import planner
from ..sources import tables
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


_MONTH = "((year({0}) - 1995) * 12 + month({0}) - 1)::INTEGER"
_SUPP = f"sm AS (SELECT l_suppkey AS voxel, {_MONTH.format('l_shipdate')} AS t, sum(l_extendedprice * (1 - l_discount)) / 1e6 AS v FROM lineitem GROUP BY ALL)"
_SALES = f"sx AS (SELECT l_partkey AS voxel, l_partkey // 50 AS row, l_partkey % 50 AS col, {_MONTH.format('l_shipdate')} AS t, sum(l_extendedprice * (1 - l_discount)) / 1e6 AS v FROM lineitem GROUP BY ALL)"


def _supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.supplier_matrix(spark, sf_dir).withColumn("v", F.col("v") / 1e6)


@query(f"WITH {_SUPP} SELECT a.t, b.t AS t2, {q6('sum(a.v * b.v)', 'g')} FROM sm a JOIN sm b USING (voxel) GROUP BY ALL")
def a20_gram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return subspace.gram(_supplier(spark, sf_dir)).select("t", "t2", *r6("g"))


@query(f"WITH {_SUPP} SELECT {q6('sum(v * v)', 'energy')} FROM sm")
def a21_energy_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Total energy as the trace of the Gram table."""
    g = subspace.gram(_supplier(spark, sf_dir))
    return g.filter("t = t2").agg(F.sum("g").alias("energy")).select(*r6("energy"))


@query("SELECT vec_id AS id, round(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[]), 6) + 0.0 AS energy FROM embeddings WHERE vec_id % 2 = 0 UNION ALL SELECT -1, round(sum(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) + 0.0 FROM embeddings WHERE vec_id % 2 = 0")
def a21_dict_basis(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Energy of each atom in the whole basis, which a basis keeps if and only if it
    is orthonormal and complete; under -1 the sum of the squared singular values."""
    atoms = tables.vectors(spark, sf_dir, False)
    val, basis = subspace.leading(subspace.gram_packed(atoms, "x"))
    long = atoms.select("id", F.posexplode("x").alias("t", "v"))
    comps = subspace.compress(long, subspace.basis_table(spark, basis), ["id"])
    total = spark.createDataFrame([(-1, float(val.sum()))], "id long, energy double")
    return comps.groupBy("id").agg(F.sum(F.col("v") ** 2).alias("energy")).unionByName(total).select("id", *r6("energy"))


@query()
def a21_rank_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Retained energy of the vectors' leading directions: not low rank here."""
    g = subspace.gram_packed(tables.vectors(spark, sf_dir, False), "x")
    val, _ = subspace.leading(g)
    rows = [(i, float(v)) for i, v in enumerate(val)]
    return subspace.rank_energy(spark.createDataFrame(rows, "comp int, value double")).select("comp", *r6("energy", "share"))


def _cosines(spark: SparkSession, length: int, r: int) -> DataFrame:
    t, j = F.col("t"), F.col("comp")
    grid = spark.range(length).select(F.col("id").cast("int").alias("t")).crossJoin(spark.range(r).select(F.col("id").cast("int").alias("comp")))
    return grid.select("t", "comp", (F.cos(math.pi * (t + 0.5) * j / length) * F.when(j == 0, math.sqrt(1 / length)).otherwise(math.sqrt(2 / length))).alias("re"), F.lit(0.0).alias("im"))


_COS = "cb AS (SELECT t::INTEGER AS t, j::INTEGER AS comp, cos(pi() * (t + 0.5) * j / 84) * CASE WHEN j = 0 THEN sqrt(1.0::DOUBLE / 84) ELSE sqrt(2.0::DOUBLE / 84) END AS b FROM range(84) a(t), range(10) c(j))"
_COMP = f"{_SUPP}, {_COS}, cx AS (SELECT voxel, comp, sum(v * b) AS v FROM sm JOIN cb USING (t) GROUP BY ALL)"


@query(f"WITH {_COMP} SELECT voxel, comp, {q6('v', 'v')} FROM cx")
def a22_compress(spark: SparkSession, sf_dir: str) -> DataFrame:
    return subspace.compress(_supplier(spark, sf_dir), _cosines(spark, 84, 10), ["voxel"]).select("voxel", "comp", *r6("v"))


@query(f"WITH {_COMP}, dx AS (SELECT voxel, cb.t, sum(cx.v * b) AS v FROM cx JOIN cb USING (comp) GROUP BY ALL) SELECT voxel, {q6('sqrt(sum(power(sm.v - dx.v, 2)))', 'err')} FROM sm JOIN dx USING (voxel, t) GROUP BY voxel")
def a23_roundtrip_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, b = _supplier(spark, sf_dir), _cosines(spark, 84, 10)
    back = subspace.decompress(subspace.compress(x, b, ["voxel"]), b, ["voxel"]).withColumnRenamed("v", "w")
    return x.join(back, ["voxel", "t"]).groupBy("voxel").agg(F.sqrt(F.sum((F.col("v") - F.col("w")) ** 2)).alias("err")).select("voxel", *r6("err"))


def _calibrated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """voxel, rank, v: ten cosine components turned into the calibrated basis."""
    x, b = _supplier(spark, sf_dir), _cosines(spark, 84, 10)
    w = subspace.autocal(x, b, 10, ["voxel"])
    c = subspace.compress(x, b, ["voxel"])
    table = spark.createDataFrame([(i, j, float(v)) for i, line in enumerate(w) for j, v in enumerate(line)], "comp int, rank int, w double")
    return c.join(F.broadcast(table), "comp").groupBy("voxel", "rank").agg(F.sum(F.col("v") * F.col("w")).alias("v"))


@query(f"WITH {_COMP} SELECT voxel, {q6('sum(v * v)', 'energy')} FROM cx GROUP BY voxel")
def a24_autocal_basis(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Energy of each voxel after calibration at full rank: a rotation keeps it."""
    return _calibrated(spark, sf_dir).groupBy("voxel").agg(F.sum(F.col("v") ** 2).alias("energy")).select("voxel", *r6("energy"))


@query()
def a24_autocal_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Energy that a calibrated basis of rank r keeps of ten cosine components."""
    per = _calibrated(spark, sf_dir).groupBy(F.col("rank").alias("comp")).agg(F.sum(F.col("v") ** 2).alias("value"))
    return subspace.rank_energy(per).select("comp", *r6("energy", "share"))


@query(f"WITH {_SUPP} SELECT r.rank, {q6('sum(v * v)', 'energy')} FROM sm, (VALUES (1), (5), (20), (84)) r(rank) GROUP BY r.rank")
def a26_rank_project(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Energy of the projection plus that of what it leaves, at several ranks: a
    projection parts them at right angles."""
    x, out = _supplier(spark, sf_dir), None
    for r in (1, 5, 20, 84):
        y = subspace.rank_project(x, r, ["voxel"]).withColumnRenamed("v", "w")
        v, w = F.coalesce("v", F.lit(0.0)), F.coalesce("w", F.lit(0.0))
        one = x.join(y, ["voxel", "t"], "full").agg(F.lit(r).alias("rank"), F.sum((v - w) ** 2 + w * w).alias("energy"))
        out = one if out is None else out.unionByName(one)
    return out.select("rank", *r6("energy"))


@query()
def a26_rank_tail(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Squared distance to the rank-5 projection; equals the energy of the tail."""
    x = _supplier(spark, sf_dir)
    y = subspace.rank_project(x, 5, ["voxel"]).withColumnRenamed("v", "w")
    return x.join(y, ["voxel", "t"], "full").agg(F.sum((F.coalesce("v", F.lit(0.0)) - F.coalesce("w", F.lit(0.0))) ** 2).alias("tail")).select(*r6("tail"))


@query(
    f"""WITH {_SUPP}, a AS (SELECT voxel, sum(v) AS a FROM sm GROUP BY voxel), b AS (SELECT t, sum(v) / 1000 AS b FROM sm GROUP BY t),
s AS (SELECT sqrt((SELECT sum(a * a) FROM a) * (SELECT sum(b * b) FROM b)) AS s)
SELECT voxel, t, {q6('a * b * greatest(s - 0.5, 0) / s', 'v')} FROM a, b, s"""
)
def a27_nuclear_prox(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The prox of the product of suppliers' and months' sums, a matrix of rank one:
    its one singular value is lowered, and the matrix shrinks in that proportion."""
    x = _supplier(spark, sf_dir)
    a = x.groupBy("voxel").agg(F.sum("v").alias("a"))
    b = x.groupBy("t").agg((F.sum("v") / 1000).alias("b"))
    product = a.join(F.broadcast(b)).select("voxel", "t", (F.col("a") * F.col("b")).alias("v"))  # 84 months
    return subspace.nuclear_prox(product, 0.5, ["voxel"]).select("voxel", "t", *r6("v"))


@query("WITH s(i, v) AS (VALUES (0, 3.0), (1, 1.5), (2, 0.4)) SELECT i, greatest(v - 0.5, 0)::DOUBLE AS v FROM s")
def a27_soft_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Singular values of a diagonal matrix under the nuclear prox."""
    x = spark.createDataFrame([(i, j, (3.0, 1.5, 0.4)[i] if i == j else 0.0) for i in range(3) for j in range(3)], "voxel int, t int, v double")
    y = subspace.nuclear_prox(x, 0.5, ["voxel"]).filter("voxel = t")
    return y.select(F.col("voxel").alias("i"), F.round(F.col("v"), 6).alias("v"))


@query(
    f"""WITH {_SUPP}, g AS (SELECT a.t, b.t AS t2, sum(a.v * b.v) AS g FROM sm a JOIN sm b USING (voxel) GROUP BY ALL),
x0 AS (SELECT DISTINCT t, 1.0::DOUBLE AS x FROM g), y0 AS (SELECT g.t, sum(g * x) AS y FROM g JOIN x0 ON x0.t = t2 GROUP BY g.t),
x1 AS (SELECT t, y / sqrt(sum(y * y) OVER ()) AS x FROM y0), y1 AS (SELECT g.t, sum(g * x) AS y FROM g JOIN x1 ON x1.t = t2 GROUP BY g.t),
x2 AS (SELECT t, y / sqrt(sum(y * y) OVER ()) AS x FROM y1), y2 AS (SELECT g.t, sum(g * x) AS y FROM g JOIN x2 ON x2.t = t2 GROUP BY g.t)
SELECT 0 AS iter, {q6('sum(x * y) / sum(x * x)', 'value')} FROM x0 JOIN y0 USING (t) UNION ALL SELECT 1, {q6('sum(x * y) / sum(x * x)', 'value')} FROM x1 JOIN y1 USING (t) UNION ALL SELECT 2, {q6('sum(x * y) / sum(x * x)', 'value')} FROM x2 JOIN y2 USING (t)"""
)
def a29b_power_iter(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = subspace.gram(_supplier(spark, sf_dir))
    return subspace.power_values(g, 3).select("iter", *r6("value"))


# --- matching: even vectors are atoms, odd ones voxels -----------------------------------

_VEC = "av AS (SELECT vec_id AS atom_id, label, embedding::DOUBLE[] AS a FROM embeddings WHERE vec_id % 2 = 0), vv AS (SELECT vec_id AS id, label, embedding::DOUBLE[] AS x FROM embeddings WHERE vec_id % 2 = 1)"
_NORM = "sqrt(list_inner_product(a, a))"
_BEST = "QUALIFY row_number() OVER (PARTITION BY id ORDER BY score DESC, atom_id) = 1"
_REAL = f"{_VEC}, m AS (SELECT id, x, atom_id, a, round(list_inner_product(a, x) / {_NORM}, 9) AS score FROM vv, av {_BEST})"


def _pair(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    return tables.vectors(spark, sf_dir, True), matching.with_norm(tables.vectors(spark, sf_dir, False))


@query(f"WITH {_REAL} SELECT id, atom_id, {q6('score', 'score')} FROM m")
def a30_match_real(spark: SparkSession, sf_dir: str) -> DataFrame:
    v, a = _pair(spark, sf_dir)
    return planner.match(v, a, "real").select("id", "atom_id", *r6("score"))


@query(
    f"""WITH {_VEC}, s AS (SELECT id, atom_id, list_inner_product(a, x) AS re, list_sum(list_transform(range(0, 64, 2), lambda i: a[i + 2] * x[i + 1] - a[i + 1] * x[i + 2])) AS im, {_NORM} AS n FROM vv, av)
SELECT id, atom_id, {q6('score', 'score')} FROM (SELECT id, atom_id, round(sqrt(re * re + im * im) / n, 9) AS score FROM s {_BEST})"""
)
def a30_match_complex(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors as 32 complex numbers, by blocked matrix products."""
    v, a = _pair(spark, sf_dir)
    return matching.exhaustive_blocks(v, a, "modulus", interleaved=True).select("id", "atom_id", *r6("score"))


_DENSE = f"{_REAL}, d AS (SELECT *, greatest(list_inner_product(a, x) / power({_NORM}, 2), 0) AS rho FROM m)"


@query(f"WITH {_DENSE} SELECT id, {q6('rho', 'rho')} FROM d")
def a31_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    v, a = _pair(spark, sf_dir)
    return matching.density(planner.match(v, a, "real"), v, a).select("id", *r6("rho"))


@query(f"WITH {_REAL} SELECT m.id, av.label FROM m JOIN av USING (atom_id)")
def a32_lookup(spark: SparkSession, sf_dir: str) -> DataFrame:
    v, a = _pair(spark, sf_dir)
    return matching.lookup(planner.match(v, a, "real"), a.select("id", "label")).select("id", "label")


@query(f"WITH {_DENSE} SELECT id, {q6('rho * a[1]', 'x0')}, {q6('rho * a[64]', 'x63')} FROM d")
def a33_resynth(spark: SparkSession, sf_dir: str) -> DataFrame:
    v, a = _pair(spark, sf_dir)
    x = matching.resynth(matching.density(planner.match(v, a, "real"), v, a))
    return x.select("id", F.col("x")[0].alias("x0"), F.col("x")[63].alias("x63")).select("id", *r6("x0", "x63"))


@query(f"WITH {_VEC}, m AS (SELECT id, x, atom_id, a, round(abs(list_inner_product(a, x)) / {_NORM}, 9) AS score FROM vv, av {_BEST}), d AS (SELECT *, greatest(list_inner_product(a, x) / power({_NORM}, 2), 0) AS rho FROM m) SELECT id, atom_id, {q6('score', 'score')}, {q6('rho', 'rho')}, {q6('rho * a[1]', 'x0')} FROM d")
def a34_project(spark: SparkSession, sf_dir: str) -> DataFrame:
    v, a = _pair(spark, sf_dir)
    return matching.project(v, a, "absolute").withColumn("x0", F.col("x")[0]).select("id", "atom_id", *r6("score", "rho", "x0"))


_ROT = "cos(pi() * (i - 0.5) * j / 64) * CASE WHEN j = 0 THEN 0.125 ELSE sqrt(2.0::DOUBLE / 64) END"
_CAL = f"""{_VEC}, ra AS (SELECT atom_id, {_NORM} AS n, list_transform(range(10), lambda j: list_sum(list_transform(range(1, 65), lambda i: a[i] * {_ROT}))) AS b FROM av),
rv AS (SELECT id, list_transform(range(10), lambda j: list_sum(list_transform(range(1, 65), lambda i: x[i] * {_ROT}))) AS y FROM vv),
m AS (SELECT id, atom_id, b, y, n, round(abs(list_inner_product(b, y)) / n, 9) AS score FROM rv, ra {_BEST})"""


@query(f"WITH {_CAL} SELECT id, atom_id, {q6('score', 'score')}, {q6('greatest(list_inner_product(b, y) / (n * n), 0)', 'rho')} FROM m")
def a35_match_calibrated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Atoms rotated into ten components, correlated under their old norms."""
    v, a = _pair(spark, sf_dir)
    rot = _cosines(spark, 64, 10).select(F.col("t").alias("comp"), F.col("comp").alias("comp2"), F.col("re").alias("w"))
    rv, ra = matching.rotate(v, rot), matching.rotate(a, rot)
    return matching.density(planner.match(rv, ra, "absolute"), rv, ra).select("id", "atom_id", *r6("score", "rho"))


@query(f"WITH {_VEC} SELECT id, label, atom_id, {q6('score', 'score')} FROM (SELECT id, vv.label, atom_id, round(abs(list_inner_product(a, x)) / {_NORM}, 9) AS score FROM vv JOIN av USING (label) {_BEST})")
def a36_match_by_bin(spark: SparkSession, sf_dir: str) -> DataFrame:
    v, a = _pair(spark, sf_dir)
    return matching.by_bin(v, a, "label").select("id", "label", "atom_id", *r6("score"))


def _recall(spark: SparkSession, sf_dir: str, search) -> DataFrame:
    v, a = _pair(spark, sf_dir)
    return matching.recall(search(v, a), matching.exhaustive_blocks(v, a, "absolute")).select("voxels", *r6("recall"))


@query()
def a37_lsh(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _recall(spark, sf_dir, lambda v, a: matching.lsh(v, a, tables=64, bits=4))


_ABSOLUTE = f"WITH {_VEC} SELECT id, atom_id FROM (SELECT id, atom_id, round(abs(list_inner_product(a, x)) / {_NORM}, 9) AS score FROM vv, av {_BEST})"


@query(_ABSOLUTE)
def a37_lsh_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No hyperplane, one bucket: the same atoms as the exhaustive search."""
    return matching.lsh(*_pair(spark, sf_dir), tables=1, bits=0).select("id", "atom_id")


@query(_ABSOLUTE)
def a38_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ball tree is exact: the same atoms as the exhaustive search."""
    return matching.tree(*_pair(spark, sf_dir)).select("id", "atom_id")


@query()
def a39_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _recall(spark, sf_dir, lambda v, a: matching.group(v, a, keep=6))


@query(_ABSOLUTE)
def a39_group_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All groups kept: the same atoms as the exhaustive search."""
    return matching.group(*_pair(spark, sf_dir), groups=12, keep=12).select("id", "atom_id")


@query(f"WITH {_SUPP} SELECT 'suppliers' AS source, {q6('sum(v * v)', 'energy')} FROM sm UNION ALL SELECT 'vectors', {q6('sum(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[]))', 'energy')} FROM embeddings WHERE vec_id % 2 = 0")
def w07_spectrum_sums(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the spectra behind the sweep add up to: the energy of the data."""
    g, _ = subspace.gram_matrix(subspace.gram(_supplier(spark, sf_dir)))
    sums = [("suppliers", float(subspace.leading(g)[0].sum())), ("vectors", float(subspace.leading(subspace.gram_packed(tables.vectors(spark, sf_dir, False), "x"))[0].sum()))]
    return spark.createDataFrame(sums, "source string, energy double").select("source", *r6("energy"))


@query()
def w07_rank_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Retained energy at ranks 2 to 30 of suppliers, vectors and fingerprints."""
    from ..plans.setup import make

    rows = []
    g, _ = subspace.gram_matrix(subspace.gram(_supplier(spark, sf_dir)))
    spectra = {"suppliers": subspace.leading(g)[0], "vectors": subspace.leading(subspace.gram_packed(tables.vectors(spark, sf_dir, False), "x"))[0], "fingerprints": make(8, 100, 30, 1.5, 3.0).energy}
    for name, val in spectra.items():
        share = np.cumsum(val) / val.sum()
        rows += [(name, r, round(float(share[min(r, len(share)) - 1]), 9)) for r in (2, 4, 6, 8, 10, 15, 20, 30)]
    return spark.createDataFrame(rows, "source string, rank int, share double")


_TEXT = """gr AS (SELECT {id} AS id, (('0x' || substr(md5(lower(substr(text, i, 3))), 1, 4))::INTEGER % 256) AS t FROM (SELECT {id}, text, unnest(range(1, length(text) - 1)) AS i FROM {tab})),
{out}_c AS (SELECT id, t, count(*)::DOUBLE AS v FROM gr GROUP BY ALL), {out} AS (SELECT id, t, v / sqrt(sum(v * v) OVER (PARTITION BY id)) AS v FROM {out}_c)"""


def _text_vectors(df: DataFrame, key: str) -> DataFrame:
    """Unit vectors of hashed letter 3-grams of the whole text: id, x (256 values).

    A text is counted where it is read and leaves one row of 256 counts; rows that
    repeat an id are added up.
    """
    counts = df.select(F.col(key).alias("id"), "text").mapInArrow(grams.counts, "id long, n binary")
    same = counts.groupBy("id").agg(F.collect_list("n").alias("n"))
    return same.mapInArrow(grams.units, "id long, x array<double>")


@query(
    "WITH "
    + _TEXT.format(id="item_id", tab="benchmark", out="ba")
    + ", "
    + _TEXT.format(id="doc_id", tab="(SELECT d.* FROM documents d JOIN labels USING (doc_id) WHERE quality = 1)", out="dv").replace("gr AS", "gd AS").replace("FROM gr", "FROM gd")
    + """, s AS (SELECT d.id, b.id AS atom_id, round(sum(d.v * b.v), 9) AS score FROM dv d JOIN ba b USING (t) GROUP BY ALL)
SELECT id AS doc_id, atom_id AS item_id, round(score, 6) + 0.0 AS score FROM (SELECT * FROM s QUALIFY row_number() OVER (PARTITION BY id ORDER BY score DESC, atom_id) = 1)"""
)
def w12_text_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts that are marked good matched to benchmark items by 3-gram prints."""
    marked = tables.read(spark, sf_dir, "labels").filter("quality = 1").select("doc_id")
    docs = _text_vectors(tables.read(spark, sf_dir, "documents").join(marked, "doc_id"), "doc_id")
    atoms = _text_vectors(tables.read(spark, sf_dir, "benchmark"), "item_id").withColumn("norm", F.lit(1.0))
    best = matching.exhaustive_blocks(docs, atoms, "real").filter("score > 0")  # no common gram, no match
    return best.select(F.col("id").alias("doc_id"), F.col("atom_id").alias("item_id"), "score").select("doc_id", "item_id", *r6("score"))


@query(f"WITH {_REAL} SELECT vv.label, count(*) AS voxels, {q6('avg((vv.label = av.label)::INTEGER)', 'agreement')} FROM m JOIN vv USING (id) JOIN av USING (atom_id) GROUP BY vv.label")
def w13_vector_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often a vector's best atom carries its label."""
    v, a = _pair(spark, sf_dir)
    m = matching.lookup(planner.match(v, a, "real"), a.select("id", F.col("label").alias("found"))).join(v.select("id", "label"), "id")
    return m.groupBy("label").agg(F.count("*").alias("voxels"), F.avg((F.col("label") == F.col("found")).cast("double")).alias("agreement")).select("label", "voxels", *r6("agreement"))


@query(f"WITH om AS (SELECT o_custkey AS voxel, {_MONTH.format('o_orderdate')} AS t, sum(o_totalprice) / 1e6 AS v FROM orders GROUP BY ALL) SELECT l.length, count(*) AS cells, {q6('sum(v * v)', 'energy')} FROM om JOIN (VALUES (20), (40), (60), (80)) l(length) ON t < l.length GROUP BY l.length")
def w16_prefix_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One long acquisition, all shorter ones as prefixes, in one pass."""
    lengths = spark.createDataFrame([(20,), (40,), (60,), (80,)], "length int")
    m = tables.orders_matrix(spark, sf_dir).withColumn("v", F.col("v") / 1e6)
    out = m.join(F.broadcast(lengths), F.col("t") < F.col("length")).groupBy("length")
    return out.agg(F.count("*").alias("cells"), F.sum(F.col("v") ** 2).alias("energy")).select("length", "cells", *r6("energy"))


@query(f"WITH {_SALES}, s AS (SELECT t, row, col, v FROM sx) SELECT o.t, {q6('sum(sqrt(power(coalesce(d.v - o.v, 0), 2) + power(coalesce(r.v - o.v, 0), 2)))', 'tv')}, count(*) AS cells FROM s o LEFT JOIN s d ON d.t = o.t AND d.row = o.row + 1 AND d.col = o.col LEFT JOIN s r ON r.t = o.t AND r.col = o.col + 1 AND r.row = o.row GROUP BY o.t")
def a40_sales_variation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Total variation of the sales grid month by month; a missing cell has no
    difference, so neighbours are joined by key and not taken from a window."""
    s = tables.sales_matrix(spark, sf_dir).withColumn("v", F.col("v") / 1e6).select("t", "row", "col", "v")
    down = s.select("t", (F.col("row") - 1).alias("row"), "col", F.col("v").alias("d"))
    right = s.select("t", "row", (F.col("col") - 1).alias("col"), F.col("v").alias("r"))
    x = s.join(down, ["t", "row", "col"], "left").join(right, ["t", "row", "col"], "left")
    step = lambda c: F.coalesce(F.col(c) - F.col("v"), F.lit(0.0)) ** 2
    return x.groupBy("t").agg(F.sum(F.sqrt(step("d") + step("r"))).alias("tv"), F.count("*").alias("cells")).select("t", *r6("tv"), "cells")
