"""Repeats within one document, at every distance."""

from __future__ import annotations

from tissuemap.llm import substring_dedup

from .test_operators import slow_dedup


def test_lines_of_every_length_repeated_in_one_document(spark):
    texts = [" ".join([f"p{k}w{i}" for i in range(k)] * max(3, -(-60 // k))) for k in range(1, 41)]
    texts.append(" ".join([f"line{i}" for i in range(13)] * 10))
    half = [f"g{i}" for i in range(8)]
    texts.append(" ".join((half + ["a", "b"] + half + ["c", "d", "e", "f"]) * 4))
    rows = [(i, t) for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring_dedup.dedup(docs).collect()}
    assert got == slow_dedup(rows)
    assert all(v[1] for v in got.values())
