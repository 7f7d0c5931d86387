"""The five stages against brute force, one by one and as a whole."""

from __future__ import annotations

import corpus_pipeline
import numpy as np
from tissuemap.llm import packing, quality_rules

from .test_operators import DOCS, PATH, corpus, slow_components, slow_counts, slow_dedup, slow_fingerprint

NAMES = [n for n, _ in corpus_pipeline.STAGES]


def test_stages_follow_each_other(spark):
    docs = spark.createDataFrame(corpus(), DOCS)
    stage = dict(corpus_pipeline.STAGES)
    kept = stage["quality rules"](spark, docs, "")
    assert kept.columns == docs.columns
    judged = {r["doc_id"]: r["kept"] for r in quality_rules.judge(docs).collect()}
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(k for k, v in judged.items() if v)
    assert all(slow_counts(r["text"])[0] >= 50 for r in kept.collect())
    one = stage["near dedup"](spark, kept, "")
    groups = slow_components({r["doc_id"]: slow_fingerprint(r["text"]) for r in kept.collect()})
    assert sorted(r["doc_id"] for r in one.collect()) == sorted(set(groups.values()))
    cut = stage["substring dedup"](spark, one, "")
    want = slow_dedup([(r["doc_id"], r["text"]) for r in one.collect()])
    got = {r["doc_id"]: len(r["text"].split()) for r in cut.collect()}
    assert got == {k: v[0] - v[1] for k, v in want.items() if v[1] < v[0]}
    mixed = stage["mixing"](spark, cut, "")
    assert mixed.columns == docs.columns and {r["doc_id"] for r in mixed.collect()} <= set(got)
    packed = stage["packing"](spark, mixed, "").collect()
    total = sum(len(packing.encoder(PATH).encode_ordinary(r["text"])) + 1 for r in mixed.collect())
    assert sum(r["length"] for r in packed) == total


def test_run_writes_each_stage(spark, tmp_path):
    spark.createDataFrame(corpus(), DOCS).write.parquet(f"{tmp_path}/documents.parquet")
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    used = np.bincount([r["sequence_id"] for r in out], weights=[r["length"] for r in out])
    assert used.max() <= packing.SIZE


def test_empty_and_null_documents(spark):
    for rows in ([], [(None, None, None, None, None), (1, "", "en", "a", 0), (1, "", "en", "a", 0)]):
        docs = spark.createDataFrame(rows, DOCS)
        for _, stage in corpus_pipeline.STAGES:
            docs = stage(spark, docs, "")
        assert docs.count() == 0
