"""Queries of the model read a given table in Spark's tasks."""

from __future__ import annotations

import pytest
from tissuemap.queries import registry

from .test_queries import SF

READS = {
    "a01_param_grid": "part", "a02_schedule": "events", "a03_fold_signal": "part", "a03_spoiled_signal": "customer", "a04_epg_signal": "part",
    "a05_dict_norms": "customer", "a06_resample": "part", "a08_spiral_angles": "events", "a09_mask": "customer", "a10_forward_dft": "part",
}


@pytest.mark.parametrize("name", READS)
def test_reads_a_given_table(spark, name):
    df = registry.queries()[name](spark, SF)
    assert any(f.endswith(f"/{READS[name]}.parquet") for f in df.inputFiles())
