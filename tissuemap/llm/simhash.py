"""SimHash near-duplicate detection by Golay-code fuzzy hashing.

Fingerprint: each bit is the majority over the XXH64 hashes of a text's word
3-shingles. Two fingerprints link at three or fewer differing bits.

Candidate keys: the 64 bits are cut into segments of 23, 23 and 18 bits. With
three errors in all, at most one segment has two or more, so some pair of
segments has at most one error each. The perfect binary [23, 12] Golay code puts
every 23-bit word within three bits of exactly one codeword. If two words differ
in at most one bit, the codeword nearest to one lies within four bits of the
other. So an indexed fingerprint gets, per segment, the codewords within four
bits (one to six of them), and a probing one only its nearest; a pair of segments
gives 24-bit keys. Equal keys are candidates, verified by the Hamming distance.

Scale: equal fingerprints are one class first. Candidates meet in a partition
sorted by key and read as a stream, and a bucket yields a spanning forest of its
links, not all pairs, which is all that components need. Nothing is capped.

Defined results: texts without words (null, empty, blank) have fingerprint zero
and link like any other; texts of fewer than three words have one shingle;
repeated rows share a class; a null doc_id counts only if a component has no
other id; an empty table gives an empty result; extra columns play no part.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise, run_starts, text_bytes
from .components import components

SHINGLE = 3
REACH = 3
SEED = 42
#: (shift, width) of the segments of a fingerprint.
SEGMENTS = ((41, 23), (18, 23), (0, 18))
PAIRS = ((0, 1), (0, 2), (1, 2))
#: Generator polynomial of the binary Golay code, x^11+x^10+x^6+x^5+x^4+x^2+1.
GENERATOR = 0xC75
#: Buckets with more candidate pairs than this are searched block by block.
DENSE = 1 << 14


def fingerprint(text: bytes, k: int = SHINGLE) -> int:
    """Majority bits of the XXH64 hashes of the word shingles of one text."""
    words = text.lower().split()  # ASCII letters and ASCII white space only
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= k:
        return xxhash.xxh64_intdigest(joined, SEED)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate(([0], ends[:-1])).tolist()
    digest = xxhash.xxh64_intdigest
    h = np.array([digest(joined[a:b], SEED) for a, b in zip(starts, (ends[k - 1 :] - 1).tolist(), strict=False)], dtype=">u8")
    votes = np.unpackbits(h.view(np.uint8)).reshape(-1, 64).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(votes * 2 > len(h)).tobytes(), "big")


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        out = np.array([fingerprint(t) for t in text_bytes(b.column("text"))], dtype=np.uint64).view(np.int64)
        yield pa.record_batch([b.column("doc_id"), b.column("mark"), pa.array(out)], ["doc_id", "mark", "fp"])


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, hash of the text and fingerprint (a signed long) of each document."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text", F.xxhash64("text").alias("mark")).mapInArrow(_fingerprints, f"doc_id {kind}, mark long, fp long")


def _remainders(x: np.ndarray) -> np.ndarray:
    """Remainders modulo the generator polynomial of 23-bit words."""
    x = x.astype(np.int64)
    for bit in range(22, 10, -1):
        x = np.where(x >> bit & 1, x ^ (GENERATOR << (bit - 11)), x)
    return x


@cache
def codewords() -> np.ndarray:
    """All codewords, by their index: the index in the upper bits, the check below."""
    index = np.arange(4096) << 11
    return index | _remainders(index)


@cache
def _tables() -> tuple[np.ndarray, np.ndarray]:
    """By remainder: the error pattern of weight at most three, and up to five of
    weight four (0 where there are fewer), derived from the code itself."""
    near, far = np.zeros(2048, np.int64), np.zeros((2048, 5), np.int64)
    for w in range(4):
        e = np.array([sum(1 << i for i in c) for c in combinations(range(23), w)], np.int64)
        near[_remainders(e)] = e
    e = np.array([sum(1 << i for i in c) for c in combinations(range(23), 4)], np.int64)
    r = _remainders(e)
    order = np.argsort(r, kind="stable")
    e, r = e[order], r[order]
    starts = run_starts(r)
    at = np.arange(len(r)) - np.repeat(starts, np.diff(np.append(starts, len(r))))
    far[r, at] = e
    return near, far


def segment_keys(word: np.ndarray) -> np.ndarray:
    """Codeword indices within four bits of each 23-bit word: column 0 the
    nearest, then up to five more; -1 fills."""
    near, far = _tables()
    r = _remainders(word)
    first = (word ^ near[r]) >> 11
    more = np.where(far[r] > 0, (word[:, None] ^ far[r]) >> 11, -1)
    return np.column_stack([first, more])


def _emit_keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        fp = b.column("fp").to_numpy(zero_copy_only=False).view(np.uint64)
        for lo in range(0, len(fp), 20_000):
            part = fp[lo : lo + 20_000]
            keys = [segment_keys(((part >> np.uint64(s)) & np.uint64((1 << w) - 1)).astype(np.int64)) for s, w in SEGMENTS]
            signed = part.view(np.int64)
            for p, (i, j) in enumerate(PAIRS):
                a, c = keys[i], keys[j]
                both = (a[:, :, None] << 12 | c[:, None, :]) | p << 24
                good = (a >= 0)[:, :, None] & (c >= 0)[:, None, :]
                rows = np.nonzero(good)[0]
                key = np.concatenate([both[good], both[:, 0, 0]]).astype(np.int32)
                who = np.concatenate([signed[rows], signed])
                probe = np.zeros(len(key), bool)
                probe[len(rows) :] = True
                yield pa.record_batch([pa.array(key), pa.array(who), pa.array(probe)], ["key", "fp", "probe"])


def _forest(members: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links among distinct fingerprints."""
    left = np.ones(len(members), bool)
    us, vs = [], []
    for seed in range(len(members)):
        if not left[seed]:
            continue
        left[seed] = False
        todo = [seed]
        while todo:
            at = todo.pop()
            rest = np.flatnonzero(left)
            if not len(rest):
                break
            hit = rest[np.bitwise_count(members[rest] ^ members[at]) <= REACH]
            if len(hit):
                left[hit] = False
                us.append(np.full(len(hit), members[at], np.uint64))
                vs.append(members[hit])
                todo += hit.tolist()
    empty = np.zeros(0, np.uint64)
    return (np.concatenate(us), np.concatenate(vs)) if us else (empty, empty)


def _links(key: np.ndarray, fp: np.ndarray, probe: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Links within buckets; rows are sorted by key, whole buckets only."""
    starts = run_starts(key)
    length = np.diff(np.append(starts, len(key)))
    n_probe = np.add.reduceat(probe.astype(np.int64), starts) if len(starts) else starts
    work = n_probe * (length - n_probe)
    us, vs = [], []
    bucket = np.repeat(np.arange(len(starts)), length)
    sparse = np.flatnonzero(probe & ((work > 0) & (work <= DENSE))[bucket])
    for lo in range(0, len(sparse), 4096):
        mine = sparse[lo : lo + 4096]
        span = length[bucket[mine]]
        other = np.repeat(starts[bucket[mine]] - np.concatenate(([0], np.cumsum(span)[:-1])), span) + np.arange(span.sum())
        a, b = np.repeat(fp[mine], span), fp[other]
        good = (a < b) & ~probe[other] & (np.bitwise_count(a ^ b) <= REACH)
        us.append(a[good])
        vs.append(b[good])
    for at in np.flatnonzero(work > DENSE):
        u, v = _forest(np.unique(fp[starts[at] : starts[at] + length[at]]))
        us.append(u)
        vs.append(v)
    empty = np.zeros(0, np.uint64)
    return (np.concatenate(us), np.concatenate(vs)) if us else (empty, empty)


def _search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: list[tuple[np.ndarray, ...]] = []

    def out(u: np.ndarray, v: np.ndarray) -> pa.RecordBatch:
        pairs = np.unique(np.column_stack([u.view(np.int64), v.view(np.int64)]), axis=0) if len(u) else np.zeros((0, 2), np.int64)
        return pa.record_batch([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["u", "v"])

    for b in batches:
        if not b.num_rows:
            continue
        key = b.column("key").to_numpy()
        held.append((key, b.column("fp").to_numpy().view(np.uint64), b.column("probe").to_numpy(zero_copy_only=False)))
        if held[0][0][0] == key[-1] and len(held) > 1 or len(key) and key[0] == key[-1]:
            continue  # one bucket so far
        key, fp, probe = (np.concatenate(x) for x in zip(*held, strict=True))
        last = int(np.searchsorted(key, key[-1]))
        yield out(*_links(key[:last], fp[:last], probe[:last]))
        held = [(key[last:], fp[last:], probe[last:])]
    if held:
        yield out(*_links(*(np.concatenate(x) for x in zip(*held, strict=True))))


def links(distinct: DataFrame) -> DataFrame:
    """u, v: fingerprints of ``distinct`` (fp) that link, enough to connect all."""
    # a fingerprint gives some 90 rows, so the few files of fingerprints are dealt
    # to all tasks first
    spread = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    keys = distinct.select("fp").repartition(spread).mapInArrow(_emit_keys, "key int, fp long, probe boolean")
    parts = keys.repartition("key").sortWithinPartitions("key")
    return parts.mapInArrow(_search, "u long, v long").distinct()


def _labelled(docs: DataFrame) -> DataFrame:
    """doc_id, mark, fp, root, component_id of each row."""
    prints = materialise(fingerprints(docs), "prints")
    classes = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("first")), "classes")
    roots = components(links(classes))
    joined = classes.join(roots, classes.fp == roots.node, "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    joined = materialise(joined, "joined")
    ids = materialise(joined.groupBy("root").agg(F.min("first").alias("component_id")), "ids")
    labels = materialise(joined.join(ids, "root").select("fp", "root", "component_id"), "labels")
    return prints.join(labels, "fp")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, fp, component_id (smallest doc_id of the component) of each row."""
    return _labelled(docs).select("doc_id", "fp", "component_id")


def first_of(rows: DataFrame, key: str) -> DataFrame:
    """key, doc_id, mark of the first row of each key: ids in order, null after
    all others, then the hash of the text."""
    best = rows.groupBy(key).agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "mark")).alias("b"))
    return best.select(key, "b.doc_id", "b.mark")


def pick(docs: DataFrame, chosen: DataFrame) -> DataFrame:
    """One row of ``docs`` for each doc_id and mark of ``chosen``, with all its
    columns. A text belongs to one component, so these two tell rows apart."""
    from pyspark.sql import Window

    few = chosen.select(F.col("doc_id").alias("_id"), F.col("mark").alias("_of"))
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")
    body = docs.select("doc_id", F.xxhash64("text").alias("_mark"), row)
    kept = body.join(few, body.doc_id.eqNullSafe(few._id) & (body._mark == few._of), "left_semi")
    # rows of one id and text are copies of one document
    rank = F.row_number().over(Window.partitionBy("doc_id", "_mark").orderBy("_mark"))
    return kept.withColumn("_rank", rank).filter("_rank = 1").select("_row.*")


def keep_one(docs: DataFrame) -> DataFrame:
    """One document of each component, with all its columns: the smallest id.

    Of rows that repeat this id the first by text stays; rows without an id stay
    only if nothing else of their component does, and then one of them.
    """
    return pick(docs, materialise(first_of(_labelled(docs), "root"), "first"))
