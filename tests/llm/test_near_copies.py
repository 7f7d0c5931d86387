"""The near-duplicate stage: five-word shingles, similarity 0.8 or more."""

from __future__ import annotations

import random
from itertools import combinations

import corpus_pipeline
import numpy as np
import pyarrow as pa
from tissuemap.llm import near_copies

from .test_operators import words_of


def slow_kept(rows):
    """Smallest id of each component of pairs at 0.8 or more."""
    sets = {}
    for i, t in rows:
        w = words_of((t or "").lower())
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in combinations(sorted(sets), 2):
        if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
            x, y = sorted((find(a), find(b)))
            root[y] = x
    return sorted(i for i in root if root[i] == i)


def planted(seed=4):
    """Texts with copies at similarities around 0.8, and a dense group."""
    r = random.Random(seed)
    word = lambda: "".join(r.choices("abcdefgh", k=6))
    texts = []
    for n in range(40):
        base = [word() for _ in range(200)]
        near = list(base)
        for i in r.sample(range(200), n % 6):
            near[i] = word()
        texts += [" ".join(base), " ".join(near).upper()]
    base = [word() for _ in range(150)]
    for _ in range(90):
        near = list(base)
        for i in r.sample(range(150), 2):
            near[i] = word()
        texts.append(" ".join(near))
    texts += ["", None, " ", "one two", "One  two", "one two three"]
    return list(enumerate(texts))


def test_stage_matches_brute_force(spark):
    rows = planted()
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = sorted(r["doc_id"] for r in dict(corpus_pipeline.STAGES)["near dedup"](spark, docs, "").collect())
    assert got == slow_kept(rows)


def test_forest_connects_what_links():
    rng = np.random.default_rng(1)
    sets = [np.unique(np.concatenate([np.arange(g * 100, g * 100 + 90), rng.integers(10_000, 10_000_000, k)])).astype(np.uint64) for g in range(3) for k in (0, 3, 6, 60)]
    size = np.array([len(s) for s in sets])
    got = near_copies._forest(np.arange(len(sets)), np.concatenate(sets), size)
    want = {(a, b) for a, b in combinations(range(len(sets)), 2) if 5 * len(set(sets[a]) & set(sets[b])) >= 4 * len(set(sets[a]) | set(sets[b]))}
    assert {tuple(sorted(x)) for x in got} <= want and len(got) == 6
    assert {i for x in got for i in x} == {i for x in want for i in x}


def crowd(n, seed=6):
    """A large group around one text: half link with it, the others with nothing."""
    r = random.Random(seed)
    word = lambda: "".join(r.choices("abcdefgh", k=6))
    base = [word() for _ in range(150)]
    texts = [" ".join(base)]
    for k in range(n):
        near = list(base)
        for i in r.sample(range(150), 1 + k % 6):
            near[i] = word()
        texts.append(" ".join(near))
    return list(enumerate(texts))


def test_pairs_do_not_grow_with_the_square_of_a_group(spark, monkeypatch):
    made, write = {}, near_copies.materialise

    def counted(df, label="part"):
        out = write(df, label)
        made[label] = out.count()
        return out

    monkeypatch.setattr(near_copies, "materialise", counted)
    rows = crowd(600)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = sorted(r["doc_id"] for r in near_copies.keep_one(docs).collect())
    assert got == slow_kept(rows) and 200 < len(got) < 500
    assert made["classes"] == 601 and made["pairs"] < 40 * 601


def test_sketches_rule_out_no_link():
    rng = np.random.default_rng(2)
    for size in (1, 8, 146, 700, 5000):
        base = rng.integers(0, 256, (size, 16), np.uint8)
        for changed in {0, size // 20, size // 10, size // 9}:
            near = base.copy()
            near[:changed] = rng.integers(0, 256, (changed, 16), np.uint8)
            sets = [near_copies._halves(x) for x in (base, near)]
            both = len(np.intersect1d(*sets))
            assert 5 * both >= 4 * (2 * size - both)
            t = pa.table({"fp": [1, 2], "bits": [0, 0], "size": [size, size], "sketch": [near_copies.sketch(x) for x in (base, near)]})
            assert near_copies._Members(t).open(0, np.array([1])).all()
