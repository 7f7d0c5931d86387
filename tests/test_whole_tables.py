"""Queries read every row of their tables."""

from __future__ import annotations

import pytest
from tissuemap.queries import registry

from .test_queries import SF


def run(spark, name):
    return registry.queries()[name](spark, SF).collect()


def test_every_event_and_vector(spark):
    events = spark.read.parquet(f"{SF}/events.parquet")
    assert sorted(r["event_id"] for r in run(spark, "g01_math")) == sorted(r[0] for r in events.select("event_id").collect())
    vectors = {r["vec_id"]: sorted(r["embedding"], reverse=True)[:3] for r in spark.read.parquet(f"{SF}/embeddings.parquet").collect()}
    got = {}
    for r in run(spark, "i06_table_function"):
        got.setdefault(r["vec_id"], {})[r["rank"]] = r["value"]
    assert {k: [v[i] for i in range(3)] for k, v in got.items()} == {k: pytest.approx(v) for k, v in vectors.items()}


def test_every_part(spark):
    parts = spark.read.parquet(f"{SF}/part.parquet").filter("p_retailprice >= p_size").select("p_partkey").collect()
    assert sorted(r["atom_id"] for r in run(spark, "a05_dict_norms_part")) == sorted(r[0] for r in parts)


@pytest.mark.parametrize(
    ("name", "table", "key", "kept"),
    [
        ("a03_fold_signal", "part", "p_partkey", "p_retailprice >= p_size"), ("a04_epg_signal", "part", "p_partkey", "p_retailprice >= p_size"),
        ("a03_spoiled_signal", "customer", "c_custkey", "c_acctbal >= 10 * (c_nationkey + 1)"), ("a05_dict_norms", "customer", "c_custkey", "c_acctbal >= 10 * (c_nationkey + 1)"),
    ],
)
def test_every_atom_of_the_table(spark, name, table, key, kept):
    want = {r[0] for r in spark.read.parquet(f"{SF}/{table}.parquet").filter(kept).select(key).collect()}
    assert {r["atom_id"] for r in run(spark, name)} == want and len(want) > 50
