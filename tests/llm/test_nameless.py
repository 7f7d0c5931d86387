"""One row of each component stays, whatever the ids."""

from __future__ import annotations

import random

from tissuemap.llm import simhash


def test_unrelated_rows_without_or_with_one_id_all_stay(spark):
    r = random.Random(2)
    texts = [" ".join("".join(r.choices("abcdefgh", k=6)) for _ in range(60)) for _ in range(14)]
    rows = [(None, t) for t in texts[:10]] + [(5, t) for t in texts[10:]] + [(None, texts[0]), (None, texts[10]), (5, texts[11]), (3, texts[1])]
    kept = simhash.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(x["text"] for x in kept) == sorted(texts)
    assert {x["text"]: x["doc_id"] for x in kept} == {t: None for t in texts[:10]} | {t: 5 for t in texts[10:]} | {texts[1]: 3}
