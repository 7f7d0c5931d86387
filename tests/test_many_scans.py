"""Slices whose states are small are spread over the cores all the same."""

from __future__ import annotations

from tissuemap.config import EngineConfig
from tissuemap.operators import phantom
from tissuemap.plans.setup import make
from tissuemap.plans.slices import phantom_samples, reduce_samples, repeat_slices, run_slices


def test_slices_are_dealt_to_all_cores(spark):
    s = make(8, 48, 6, 1.5, 3.0, every=40)
    one = phantom_samples(spark, phantom.digital(spark, 8), 8, 48, s.mask)
    many = repeat_slices(one, 16)
    maps = run_slices(reduce_samples(many, [s]), [s], ["seq_fixed"], EngineConfig(lam=1e-3, k_max=2))
    ids = maps.rdd.mapPartitions(lambda rows: [{r["slice_id"] for r in rows}]).collect()
    assert sorted(i for part in ids for i in part) == list(range(16)) and sum(bool(part) for part in ids) > 4
