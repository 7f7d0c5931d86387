"""Classifier scores by definition, and the cases of operators on other tables."""

from __future__ import annotations

import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from tissuemap.llm import html_extract, near_copies, quality_classifier, topk, url_filters

from .test_operators import OPERATORS, rows_of

MARKS = ["ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", "#*$%&|<>", "!", ".,", "\"'()-/:;=?@[\\]^_`{}~+", "\n"]


def slow_statistics(text):
    """The statistics, one character and one word at a time."""
    raw = (text or "").encode()
    words = raw.split()
    if not words:
        return [0.0] * 15
    share = [math.sqrt(sum(raw.count(c.encode()) for c in m) / len(raw)) for m in MARKS]
    lines = [x for x in raw.split(b"\n") if x.strip()]
    n = len(words)
    return [
        math.log(1 + n), math.log(sum(map(len, words)) / n), *share, len(set(words)) / n**0.9, math.sqrt(sum(a == b for a, b in zip(words, words[1:])) / n),
        math.sqrt(Counter(words).most_common(1)[0][1] / n), math.sqrt(1 - len(set(lines)) / len(lines)),
        math.sqrt(sum(w[:1].isalpha() and w[:1].isupper() and w[0] < 128 for w in words) / n), math.sqrt(sum(c > 127 for c in raw) / len(raw)),
    ]


def slow_scores(texts, labels):
    """Bayes' rule with two normal densities, matrices solved and not factored."""
    x = {i: np.array(slow_statistics(t)) for i, t in texts}
    learn = [(x[i], y) for i, y in labels if i in x and zlib.crc32(str(i).encode()) % 5]
    by = [np.array([v for v, y in learn if y == k]) for k in (0, 1)]
    cov = [np.cov(b.T, bias=True) for b in by]
    pooled = sum(len(b) * c for b, c in zip(by, cov)) / len(learn)
    out = {}
    for i, v in x.items():
        density = []
        for b, c in zip(by, cov):
            s = 0.9 * c + 0.1 * pooled
            s = 0.95 * s + 0.05 * np.diag(np.diag(s)) + 1e-4 * np.eye(15)
            gap = v - b.mean(axis=0)
            density.append(math.log(len(b) / len(learn)) - 0.5 * np.linalg.slogdet(s)[1] - 0.5 * gap @ np.linalg.solve(s, gap))
        out[i] = 1 / (1 + math.exp(min(50, max(-50, density[0] - density[1]))))
    return out


def test_scores_by_definition(spark):
    r = random.Random(6)
    texts = []
    for i in range(300):
        w = ["".join(r.choices("etaoinshrABC019.,!#é", k=r.randint(1, 8))) for _ in range(r.randint(1, 90))]
        texts.append((i, r.choice([" ", "\n"]).join(w) + r.choice(["", "\n" + " ".join(w)])))
    texts += [(900, None), (901, ""), (902, " \n ")]
    labels = [(i, int(len(t or "") % 3 > 0)) for i, t in texts[:250]] + [(3, 0), (5000, 1)]
    docs, marks = spark.createDataFrame(texts, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int")
    got, want = rows_of(quality_classifier.classify(docs, marks)), slow_scores(texts, labels)
    assert {k: v["score"] for k, v in got.items()} == pytest.approx(want, abs=1e-6)
    assert all(v["predicted"] == int(v["score"] >= 0.3) and v["held_out"] == (zlib.crc32(str(k).encode()) % 5 == 0) for k, v in got.items())


def test_classifier_cases(spark):
    labels = spark.createDataFrame([(1, 1), (2, 0), (None, 1), (3, None)], "doc_id long, quality int")
    shape = "doc_id long, text string, quality int, score double, x int, y int"
    assert quality_classifier.classify(spark.createDataFrame([], shape), labels).count() == 0
    rows = [(None, None, 1, 0.5, 1, 1), (1, "a b", 0, None, 1, 1), (1, "a b", 0, None, 1, 1), (2, "", None, None, None, None)]
    got = quality_classifier.classify(spark.createDataFrame(rows, shape), labels)
    assert got.columns == ["doc_id", "held_out", "score", "predicted"] and got.count() == 4 and got.filter("score is null").count() == 0


def test_url_rule_cases(spark):
    rules = url_filters.rule_table(spark)
    shape = "page_id long, url string, host string, prefix string, stack int"
    assert url_filters.apply_rules(spark.createDataFrame([], shape), rules).count() == 0
    rows = [(None, None, "x", None, 1), (1, "", None, None, None), (1, "http://a.org/", "y", "z", 2), (1, "http://a.org/", "y", "z", 2), (2, "http://" + "a." * 100_000 + "org/" + "b" * 1_000_000, None, None, None)]
    got = url_filters.apply_rules(spark.createDataFrame(rows, shape), rules).collect()
    assert sorted((r["page_id"] is None, r["rule"] or "") for r in got) == [(False, ""), (False, "org/"), (False, "org/"), (False, "org/"), (True, "")]
    none = url_filters.rule_table(spark, ())
    assert {(r["rule"], r["verdict"]) for r in url_filters.apply_rules(spark.createDataFrame(rows, shape), none).collect()} == {(None, "allow")}


def test_page_cases(spark):
    shape = "page_id long, url string, html string, text int, n_chars string"
    assert html_extract.main_text(spark.createDataFrame([], shape)).count() == 0
    rows = [(None, None, None, 1, "x"), (1, "u", "<p>a</p>", None, None), (1, "u", "<p>a</p>", None, None), (2, None, "<p>" + "word " * 1_000_000, None, None)]
    got = html_extract.main_text(spark.createDataFrame(rows, shape)).collect()
    assert sorted(r["n_chars"] for r in got) == [0, 1, 1, 4_999_999]


def test_search_of_empty_tables(spark):
    none = topk.integer_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>, score int, ring int, v int"))
    some = topk.integer_vectors(spark.createDataFrame([(1, [1.0]), (2, [2.0])], "vec_id long, embedding array<float>"))
    assert topk.search(none, some).count() == topk.search(some, none).count() == 0


@pytest.mark.parametrize("name", [*OPERATORS, "near copies", "classify"])
def test_very_long_texts(spark, name):
    rows = [(1, "some words of a long text " * 80_000, "a"), (2, "x" * 1_500_000, "a"), (3, " " * 1_500_000, "b"), (4, "\n".join(f"line {i} of many" for i in range(120_000)), "b")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    labels = spark.createDataFrame([(1, 1), (2, 0)], "doc_id long, quality int")
    run = {**OPERATORS, "near copies": near_copies.keep_one, "classify": lambda d: quality_classifier.classify(d, labels)}[name]
    assert run(docs).collect() or name in ("keep", "mixed")
