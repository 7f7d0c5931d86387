"""Suffix trees of the substring dedup: groups, lengthened prefixes, order of ids."""

from __future__ import annotations

import random

import numpy as np
import pyarrow as pa
import pytest
from tissuemap.llm import substring_dedup

from .test_operators import slow_dedup


def repetitive(seed, n=40):
    """Texts that share passages of many lengths, on few words, with periods."""
    r = random.Random(seed)
    words = [f"w{i}" for i in range(r.choice([2, 5, 60]))]
    make = lambda k: r.choices(words, k=k)
    shared = [make(r.randint(8, 60)) for _ in range(6)]
    out = []
    for i in range(n):
        w = make(r.randint(0, 30))
        for _ in range(r.randint(0, 4)):
            w += r.choice(shared) * r.choice([1, 1, 1, 3]) + make(r.randint(0, 12))
        out.append((i, " ".join(w)))
    return out


def solve_locally(rows):
    """The groups of a corpus without Spark, each document a chunk of its own."""
    suffixes, gone = [], {}
    mark = lambda spans: [gone.setdefault(d, set()).update(range(s, s + k + 19)) for d, _, s, k in zip(*(x.to_pylist() for x in spans), strict=True)]

    class Held:
        def __init__(self, value):
            self.value = value

    for doc, text in rows:
        b = pa.record_batch([pa.array([doc]), pa.array([0]), pa.array([text])], ["doc", "mark", "text"])
        for out in substring_dedup._suffixes(Held(b"\xff" * 64), Held(b""))(iter([b])):
            settled = out.column("words").is_null().to_pylist()
            if all(settled):
                mark([out.column(c) for c in ("doc", "mark", "start", "n")])
            else:
                suffixes += out.to_pylist()
    suffixes.sort(key=lambda x: x["prefix"])
    if suffixes:
        table = pa.Table.from_pylist(suffixes)
        c = {x: table.column(x).to_numpy() for x in ("prefix", "doc", "mark", "start", "n", "at")}
        mark(substring_dedup._spans(*substring_dedup.repeated(**c, lines=table.column("words").to_pylist())))
    return {d: len(gone.get(d, ())) for d, _ in rows}


@pytest.mark.parametrize("seed", range(30))
def test_nodes_of_the_trees_give_all_repeats(seed):
    rows = repetitive(seed)
    assert solve_locally(rows) == {k: v[1] for k, v in slow_dedup(rows).items()}


@pytest.mark.parametrize(("group", "bits"), [(1, 1 << 20), (7, 64), (substring_dedup.GROUP, 1 << 20), (substring_dedup.GROUP, 64)])
def test_bounds_of_groups_and_filter_do_not_matter(spark, group, bits, monkeypatch):
    monkeypatch.setattr(substring_dedup, "HOT", 1 << 40)
    monkeypatch.setattr(substring_dedup, "FILTER_BITS", (64, bits))
    rows = [(1000 * seed + i, t) for seed in (2, 3, 5) for i, t in repetitive(seed)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(9)
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring_dedup.dedup(docs, group).collect()}
    assert got == slow_dedup(rows)


def test_words_decide_where_prefixes_collide():
    line = [b" ".join(b"%s%d" % (c, i) for i in range(20)) for c in (b"a", b"b", b"a")]
    zero = np.zeros(3, np.int64)
    doc, mark, start = substring_dedup.repeated(zero, np.arange(3), zero, zero, zero + 1, zero + 5, line)
    assert (doc.tolist(), mark.tolist(), start.tolist()) == ([2], [0], [0])


def test_ids_without_value_and_of_other_types(spark):
    text = " ".join(f"w{i}" for i in range(30))
    top = (1 << 63) - 1
    rows = [(None, text), (top, text), (None, text + " x"), (7, text)]
    got = substring_dedup.dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted((r["doc_id"] is None, r["n_removed"]) for r in got) == [(False, 0), (False, 30), (True, 30), (True, 30)]
    got = substring_dedup.dedup(spark.createDataFrame(rows[:2], "doc_id long, text string")).collect()
    assert {r["doc_id"]: r["n_removed"] for r in got} == {None: 30, top: 0}
    named = spark.createDataFrame([("b", text), ("a", text), (None, text)], "doc_id string, text string")
    got = {r["doc_id"]: r["n_removed"] for r in substring_dedup.dedup(named).collect()}
    assert got[None] == 30 and sorted((got["a"], got["b"])) == [0, 30]
