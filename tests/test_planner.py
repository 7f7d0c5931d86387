"""Strategy choice, the SQL entry points and the phantom source."""

from __future__ import annotations

from tissuemap import catalog
from tissuemap.operators import matching, phantom
from tissuemap.plans import planner
from tissuemap.plans.setup import make
from tissuemap.plans.slices import phantom_samples
from tissuemap.sources.tables import vectors

SF = "/root/testdata/sf0.001"


def test_choices():
    small, large = planner.choose(100, 100, 10, 8, 24), planner.choose(10**9, 5366, 200, 256, 3000)
    assert (small.matching, small.normal, small.reconstruction) == ("nested-loop join", "kernel per cell", "joins")
    assert (large.matching, large.normal, large.reconstruction) == ("blocked products", "mask times basis", "one task per slice")
    assert "matching: blocked" in large.explain()


def test_strategies_agree(spark):
    v, a = vectors(spark, SF, True), matching.with_norm(vectors(spark, SF, False))
    key = lambda df: sorted((r["id"], r["atom_id"]) for r in df.collect())
    assert key(planner.match(v, a, "absolute")) == key(matching.exhaustive_blocks(v, a, "absolute"))
    assert key(planner.match(v, a, "modulus")) == key(matching.exhaustive_blocks(v, a, "modulus", True))


def test_sql_entry_points(spark, tmp_path):
    catalog.install(spark, SF)
    assert spark.sql("SELECT cx_abs(3, 4) AS a, rel_err(3, 2) AS b, month_index(TIMESTAMP '1996-02-01') AS c").first()[:] == (5.0, 0.5, 13)
    assert spark.sql("SELECT count(*) FROM nation JOIN region ON n_regionkey = r_regionkey").first()[0] == 25
    s = make(8, 48, 6, 1.5, 3.0, every=40)
    maps = catalog.reconstruct(phantom_samples(spark, phantom.digital(spark, 8), 8, 48, s.mask), s, "seq_bt", "maps", rank=6, k_max=2)
    assert spark.sql("SELECT count(*) FROM maps").first()[0] == 64
    catalog.write_maps(maps, f"{tmp_path}/maps")
    assert spark.read.parquet(f"{tmp_path}/maps").filter("slice_id = 0").count() == 64


def test_phantom_source_equals_the_plan(spark):
    from tissuemap.sources.phantom_source import register

    register(spark)
    a = sorted((r["row"], r["col"], r["class"] if r["class"] is not None else -1) for r in spark.read.format("phantom").option("n", "24").load().collect())
    b = sorted((r["row"], r["col"], r["class"] if r["class"] is not None else -1) for r in phantom.digital(spark, 24).collect())
    assert a == b
