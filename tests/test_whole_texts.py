"""Text prints cover the whole text."""

from __future__ import annotations

import hashlib
import math
from collections import Counter

import pytest
from tissuemap.queries import vectors


def slow_print(text):
    c = Counter(int(hashlib.md5(text[i : i + 3].lower().encode()).hexdigest()[:4], 16) % 256 for i in range(len(text) - 2))
    norm = math.sqrt(sum(v * v for v in c.values()))
    return {t: v / norm for t, v in c.items()}


def test_prints_of_long_texts_match_brute_force(spark):
    texts = {1: "abc " * 100 + "a passage far behind the four hundredth letter", 2: "short text", 3: "ab"}
    got = {}
    for r in vectors._text_vectors(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), "doc_id").collect():
        got[r["id"]] = {t: v for t, v in enumerate(r["x"]) if v}
    assert got == {i: pytest.approx(slow_print(texts[i])) for i in (1, 2)}


def test_a_late_passage_decides_the_match(spark, tmp_path):
    late = "quantum zebra juggling fox " * 60
    spark.createDataFrame([(1, "x y z " * 67 + late)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, 1)], "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, "x y z " * 20), (2, late)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert vectors.w12_text_match(spark, str(tmp_path)).first()["item_id"] == 2
