"""Matching where atoms and voxels are many, or many of them alike."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F
from tissuemap.operators import matching


def copies(spark, seed=3):
    """Voxels and atoms of two bins, every atom five times in a shuffled order of ids."""
    rng = np.random.default_rng(seed)
    base = rng.normal(size=(120, 64)).astype(np.float32).astype(float)
    ids = rng.permutation(600)
    atoms = [(int(ids[i]), int(i % 120 % 2), base[i % 120].tolist()) for i in range(600)]
    voxels = [(i, i % 3 if i % 3 < 2 else None, rng.normal(size=64).tolist()) for i in range(90)]
    return spark.createDataFrame(voxels, "id long, label int, x array<double>"), matching.with_norm(spark.createDataFrame(atoms, "id long, label int, x array<double>"))


def first_of_best(v, atoms):
    score = {i: round(abs(float(np.dot(v, x))) / float(np.linalg.norm(x)), 9) for i, x in atoms}
    return min(score, key=lambda i: (-score[i], i))


@pytest.mark.parametrize("limit", [matching.ATOM_BYTES, 40_000])
def test_bins_make_no_pairs_and_copies_go_to_the_first(spark, limit):
    v, a = copies(spark)
    out = matching.by_bin(v, a, "label", limit=limit)
    assert "Join" not in out._jdf.queryExecution().executedPlan().toString()
    rows = a.collect()
    want = {r["id"]: first_of_best(r["x"], [(s["id"], s["x"]) for s in rows if s["label"] == r["label"]]) for r in v.filter(F.col("label").isNotNull()).collect()}
    assert {r["id"]: r["atom_id"] for r in out.collect()} == want


def test_tree_gives_copies_to_the_first(spark):
    v, a = copies(spark)
    rows = [(r["id"], r["x"]) for r in a.collect()]
    want = {r["id"]: first_of_best(r["x"], rows) for r in v.collect()}
    for leaf in (4, 256):
        assert {r["id"]: r["atom_id"] for r in matching.tree(v, a, leaf=leaf).collect()} == want


@pytest.mark.parametrize("kind", ["real", "complex"])
def test_products_stay_in_cache(kind):
    """A slice's matching takes a few megabytes beside its result, however many voxels."""
    import tracemalloc

    rng = np.random.default_rng(5)
    x, d = rng.normal(size=(2048, 4)) + 1j * rng.normal(size=(2048, 4)), rng.normal(size=(6000, 4))
    d = d if kind == "real" else d + 1j * rng.normal(size=d.shape)
    norms = np.linalg.norm(d, axis=1)
    tracemalloc.start()
    at, top = matching.best_atoms(x, d, norms)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    score = np.abs(x.conj() @ (d / norms[:, None]).T)
    assert (at == score.argmax(axis=1)).all() and top == pytest.approx(score.max(axis=1))
    assert peak < 8 << 20
