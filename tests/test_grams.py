"""Hashed 3-grams of texts against their definition."""

from __future__ import annotations

import hashlib
from collections import Counter

import pytest
from tissuemap.operators import grams
from tissuemap.queries import vectors

TEXTS = ["", "ab", "abc", "ABCabc abc", "İstanbul ΣΑΣ straße", "\x00\x00\x00a", "日本語の文字 🎉🎉🎉🎉", "xy" * 300]


def slow(text):
    low = [c.lower()[0] for c in text]
    out = Counter(int(hashlib.md5("".join(low[i : i + 3]).encode()).hexdigest()[:4], 16) % 256 for i in range(len(low) - 2))
    return [out[k] for k in range(256)]


@pytest.mark.parametrize("table", [1 << 24, 1])
def test_counts(monkeypatch, table):
    monkeypatch.setattr(grams, "TABLE", table)
    assert grams.count_texts(TEXTS).tolist() == [slow(t) for t in TEXTS]


def test_vectors_count_a_text_in_one_row(spark):
    rows = [*enumerate(TEXTS), (3, "more of three"), (50, None)]
    out = vectors._text_vectors(spark.createDataFrame(rows, "k long, text string").repartition(3), "k")
    assert "Generate" not in out._jdf.queryExecution().executedPlan().toString()
    want = {i: slow(t) for i, t in enumerate(TEXTS) if len(t) > 2}
    want[3] = [a + b for a, b in zip(want[3], slow("more of three"), strict=True)]
    got = {r["id"]: r["x"] for r in out.collect()}
    assert got == {i: pytest.approx([v / sum(w * w for w in x) ** 0.5 for v in x]) for i, x in want.items()}
