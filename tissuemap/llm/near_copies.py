"""Near copies: SimHash with Golay keys over five-word shingles, decided exactly.

Two texts link when the Jaccard similarity of their sets of word 5-shingles is at
least 4/5. Candidates come from the operator of :mod:`simhash` with a wider reach.
At 4/5 about one bit in seven of a fingerprint differs, far beyond three of 64, so
segments are decoded by their votes and not only by their bits: a segment is the
sums of votes of 23 hash bits, and its keys are the ``NEAREST`` Golay codewords that
agree with them best. Bits with narrow votes, the ones that differ between near
copies, weigh little there. Of three segments two must share a codeword, by which
two texts at 4/5 meet with a probability of 0.993, at 9/10 of 0.9997 (measured on
votes of that correlation). Candidates whose other 64 bits differ in more than
``FAR`` places are left out (a pair at 4/5 is, once in 5000), and every other one is
decided by the sets themselves, so no link is false.

Scale: equal sets are one class first. A bucket with up to ``SMALL`` classes that have
a candidate gives all its candidates, decided by a join. In a larger one, sketches rule
out pairs: bit i of a sketch is the parity of the shingles that fall to i, so two sets
differ in at least as many shingles as their sketches in bits, and no link is lost. The
pairs left are spanned by a forest, one parent for each member, and its edges alone are
decided by the join. Only where a bucket then still holds pairs between components do
their members take their sets along, and a spanning forest of their links is found by
searching outwards from one member at a time. So a class gives at most as many rows as
it has keys, however large its group. Nothing is capped.

Defined results: texts without words have the empty set and are one class; texts
of fewer than five words have one shingle; ASCII letters count without case; see
``simhash.keep_one`` for ids.
"""

from __future__ import annotations

from collections import deque
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
from .simhash import codewords, first_of, pick

SHINGLE = 5
#: Least similarity of a link, as a fraction.
LEAST = (4, 5)
#: Bits of a segment, number of segments, codewords that each gives.
WIDTH, SEGMENTS, NEAREST = 23, 3, 6
#: Most differing bits, of the 64 beside the segments, of a candidate.
FAR = 20
#: Buckets with more classes than this that have a candidate are spanned by a forest.
SMALL = 6
#: Buckets with more classes than this are compared a member at a time.
BLOCK = 64
#: Bits of a sketch, as a power of two.
SKETCH = 10


#: Columns of a class.
CLASS = ["fp", "bits", "codes", "size", "sketch"]
CLASS_TYPES = "fp long, bits long, codes binary, size long, sketch binary"


def shingle_hashes(text: bytes, k: int = SHINGLE) -> np.ndarray:
    """128-bit hashes of the distinct word shingles of one text, as rows of bytes in
    order of their first half."""
    words = text.lower().split()  # ASCII letters and ASCII white space only
    if not words:
        return np.zeros((0, 16), np.uint8)
    joined = b" ".join(words)
    digest = xxhash.xxh3_128_digest
    if len(words) <= k:
        raw = digest(joined)
    else:
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
        starts = np.concatenate(([0], ends[:-1])).tolist()
        raw = b"".join([digest(joined[a:b]) for a, b in zip(starts, (ends[k - 1 :] - 1).tolist(), strict=False)])
    rows = np.frombuffer(raw, np.uint8).reshape(-1, 16)
    return rows[np.unique(_halves(rows), return_index=True)[1]]


def _halves(rows: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(rows).view(np.uint64)[:, 0]


def votes(rows: np.ndarray) -> np.ndarray:
    """Per bit: hashes that set it less those that do not."""
    out = np.zeros(128, np.int64)
    for lo in range(0, len(rows), 1 << 16):
        out += np.unpackbits(rows[lo : lo + (1 << 16)], axis=1).sum(axis=0, dtype=np.int64)
    return 2 * out - len(rows)


@cache
def _signs() -> np.ndarray:
    return ((codewords()[None, :] >> np.arange(WIDTH)[:, None] & 1) * 2 - 1).astype(np.float32)


def segment_codes(v: np.ndarray) -> np.ndarray:
    """Indices of the best codewords: texts x SEGMENTS x NEAREST, ascending."""
    out = np.zeros((len(v), SEGMENTS, NEAREST), np.int16)
    tie = 0.4 * np.cos(np.arange(WIDTH * SEGMENTS))  # equal sums are told apart alike in all texts
    x = (v[:, : WIDTH * SEGMENTS] + tie).astype(np.float32)
    for lo in range(0, len(v), 512):
        for s in range(SEGMENTS):
            score = x[lo : lo + 512, s * WIDTH : (s + 1) * WIDTH] @ _signs()
            out[lo : lo + 512, s] = np.sort(np.argpartition(-score, NEAREST, axis=1)[:, :NEAREST], axis=1)
    return out


def sketch(rows: np.ndarray) -> bytes:
    """Parities of the numbers of hashes that fall to each bit."""
    return np.packbits(np.bincount((_halves(rows) >> np.uint64(64 - SKETCH)).astype(np.int64), minlength=1 << SKETCH) & 1 == 1).tobytes()


def _prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        fp, size, parities, v = [], [], [], np.zeros((b.num_rows, 128), np.int64)
        for i, text in enumerate(text_bytes(b.column("text"))):
            rows = shingle_hashes(text)
            fp.append(xxhash.xxh64_intdigest(_halves(rows).tobytes()) - (1 << 63))
            size.append(len(rows))
            parities.append(sketch(rows))
            v[i] = votes(rows)
        bits = np.packbits(v[:, 64:] > 0, axis=1).view(np.int64)[:, 0] if b.num_rows else np.zeros(0, np.int64)
        codes = [x.tobytes() for x in segment_codes(v)]
        yield pa.record_batch([b.column("doc_id"), b.column("mark"), pa.array(fp, pa.int64()), pa.array(bits), pa.array(codes, pa.binary()), pa.array(size, pa.int64()), pa.array(parities, pa.binary())], ["doc_id", "mark", *CLASS])


def _keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    pairs = list(combinations(range(SEGMENTS), 2))
    for b in batches:
        if not b.num_rows:
            continue
        codes = np.frombuffer(b"".join(b.column("codes").to_pylist()), np.int16).reshape(-1, SEGMENTS, NEAREST).astype(np.int32)
        key = np.stack([p << 24 | codes[:, i, :, None] << 12 | codes[:, j, None, :] for p, (i, j) in enumerate(pairs)], axis=1).reshape(len(codes), -1)
        fp, bits = (np.repeat(b.column(c).to_numpy(), key.shape[1]) for c in ("fp", "bits"))
        yield pa.record_batch([pa.array(key.ravel()), pa.array(fp), pa.array(bits)], ["key", "fp", "bits"])


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        s = [_halves(shingle_hashes(t)) for t in text_bytes(b.column("text"))]
        fp = [xxhash.xxh64_intdigest(x.tobytes()) - (1 << 63) for x in s]
        yield pa.record_batch([pa.array(fp, pa.int64()), pa.array([x.view(np.int64) for x in s], pa.list_(pa.int64()))], ["fp", "shingles"])


def _whole_buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The rows, sorted by key, in tables that do not part a bucket."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        held.append(b)
        if held[0].column("key")[0] == b.column("key")[-1]:
            continue  # one bucket so far
        t = pa.Table.from_batches(held)
        key = t.column("key").to_numpy()
        last = int(np.searchsorted(key, key[-1]))
        yield t.slice(0, last)
        held = t.slice(last).to_batches()
    if held:
        yield pa.Table.from_batches(held)


def _buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The rows of each bucket."""
    for t in _whole_buckets(batches):
        at = run_starts(t.column("key").to_numpy())
        for lo, hi in zip(at, np.append(at[1:], t.num_rows), strict=True):
            yield t.slice(lo, hi - lo)


def _near(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count((a ^ b).view(np.uint64)) <= FAR


def _by_distance(fp: np.ndarray, bits: np.ndarray) -> np.ndarray:
    """Members of a bucket from the nearest to the majority of their bits on."""
    each = np.unpackbits(np.ascontiguousarray(bits).view(np.uint8).reshape(-1, 8), axis=1)
    return np.lexsort((fp, (each != (2 * each.sum(axis=0, dtype=np.int64) > len(fp))).sum(axis=1)))


def _with_candidate(fp: np.ndarray, bits: np.ndarray) -> np.ndarray:
    """Which members of a bucket have a candidate there."""
    live = np.zeros(len(fp), bool)
    for i in _by_distance(fp, bits):
        if not live[i]:
            hit = _near(bits, bits[i])
            if np.count_nonzero(hit) > 1:  # one is the member itself
                live |= hit
    return live


def _candidates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """u, v: candidates, u < v. From large buckets key and u, each member that has a
    candidate (v null)."""
    for t in _whole_buckets(batches):
        key, fp, bits = (t.column(c).to_numpy() for c in ("key", "fp", "bits"))
        starts = run_starts(key)
        length = np.diff(np.append(starts, len(key)))
        bucket = np.repeat(np.arange(len(starts)), length)
        live, us, vs = np.zeros(len(key), bool), [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        few = np.flatnonzero((length > 1)[bucket] & (length <= BLOCK)[bucket])
        for lo in range(0, len(few), 1 << 16):
            mine = few[lo : lo + (1 << 16)]
            span = length[bucket[mine]]
            other = np.repeat(starts[bucket[mine]] - (np.cumsum(span) - span), span) + np.arange(span.sum())
            at = np.repeat(mine, span)
            good = (fp[at] < fp[other]) & _near(bits[at], bits[other])
            us.append(at[good])
            vs.append(other[good])
            live[us[-1]] = live[vs[-1]] = True
        for i in np.flatnonzero(length > BLOCK):
            own = slice(starts[i], starts[i] + length[i])
            live[own] = _with_candidate(fp[own], bits[own])
        u, v = np.concatenate(us), np.concatenate(vs)
        large = (np.add.reduceat(live, starts, dtype=np.int64) > SMALL) | (length > BLOCK)
        single = ~large[bucket[u]]
        pairs = np.unique(np.column_stack([fp[u[single]], fp[v[single]]]), axis=0)
        many = np.flatnonzero(live & large[bucket])
        columns = [
            pa.concat_arrays([pa.nulls(len(pairs), pa.int32()), pa.array(key[many], pa.int32())]),
            pa.array(np.concatenate([pairs[:, 0], fp[many]])),
            pa.concat_arrays([pa.array(pairs[:, 1]), pa.nulls(len(many), pa.int64())]),
        ]
        yield pa.record_batch(columns, ["key", "u", "v"])


class _Members:
    """The classes of one bucket."""

    def __init__(self, t: pa.Table):
        self.fp, self.bits, self.size = (t.column(c).to_numpy() for c in ("fp", "bits", "size"))
        self.sketch = np.frombuffer(b"".join(t.column("sketch").to_pylist()), np.uint64).reshape(len(self.fp), -1)

    def open(self, at: int, rest: np.ndarray) -> np.ndarray:
        """Which of ``rest`` are candidates of ``at`` that the sketches do not rule out."""
        hit = _near(self.bits[rest], self.bits[at])
        some = rest[hit]
        apart = np.maximum(np.bitwise_count(self.sketch[some] ^ self.sketch[at]).sum(axis=1, dtype=np.int64), np.abs(self.size[some] - self.size[at]))
        hit[hit] = (LEAST[1] + LEAST[0]) * apart <= (LEAST[1] - LEAST[0]) * (self.size[some] + self.size[at])
        return hit


def _trees(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The members of each bucket that have an open pair, each with its parent in a
    spanning forest of these pairs (null for a root)."""
    for t in _buckets(batches):
        m = _Members(t)
        parent, rest, todo = np.full(len(m.fp), -1), _by_distance(m.fp, m.bits), deque()
        while len(rest):
            if not todo:
                todo.append(rest[0])
                rest = rest[1:]
                continue
            at = todo.popleft()
            hit = m.open(at, rest)
            if hit.any():
                parent[rest[hit]] = at
                todo.extend(rest[hit])
                rest = rest[~hit]
        child = parent >= 0
        held = child.copy()
        held[parent[child]] = True
        if held.any():
            at = pa.array(np.flatnonzero(held))
            up = pa.array(m.fp[parent[held]], mask=~child[held])
            kept = [t.column(c).combine_chunks().take(at) for c in ("key", "fp", "bits", "size", "sketch")]
            yield pa.record_batch([*kept, up], ["key", "fp", "bits", "size", "sketch", "parent"])


def _mixed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """key, fp of the members of a bucket that have an open pair with another component."""
    for t in _buckets(batches):
        root = np.unique(t.column("root").to_numpy(), return_inverse=True)[1]
        if root.max(initial=0) == 0:
            continue
        m, found = _Members(t), np.zeros(len(root), bool)
        for i in np.flatnonzero(root != np.bincount(root).argmax()):
            others = np.flatnonzero(root != root[i])
            hit = others[m.open(i, others)]
            found[hit] = True
            found[i] |= len(hit) > 0
        if found.any():
            yield pa.record_batch([t.column(c).combine_chunks().filter(pa.array(found)) for c in ("key", "fp")], ["key", "fp"])


def _forest(fp: np.ndarray, flat: np.ndarray, size: np.ndarray) -> list[tuple[int, int]]:
    """Links that connect all linked members of a bucket: from each member that is
    reached, the rest is searched for members similar to it."""
    flat = np.unique(flat, return_inverse=True)[1]
    ends = np.cumsum(size)
    own = lambda i: flat[ends[i] - size[i] : ends[i]]
    marked = np.zeros(len(flat) + 1, bool)
    rest, out, todo = np.arange(len(fp)), [], []
    pool = flat
    while len(rest):
        if not todo:
            todo, pool, rest = [int(rest[0])], pool[size[rest[0]] :], rest[1:]
            continue
        at = todo.pop()
        marked[own(at)] = True
        both = np.add.reduceat(marked[pool], np.concatenate(([0], np.cumsum(size[rest])[:-1])), dtype=np.int64)
        marked[own(at)] = False
        hit = LEAST[1] * both >= LEAST[0] * (size[rest] + size[at] - both)
        if hit.any():
            out += [(int(fp[at]), int(fp[i])) for i in rest[hit]]
            todo += rest[hit].tolist()
            pool, rest = pool[np.repeat(~hit, size[rest])], rest[~hit]
    return out


def _forests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for t in _buckets(batches):
        lists = t.column("shingles").combine_chunks()
        links = _forest(t.column("fp").to_numpy(), lists.flatten().to_numpy(), lists.value_lengths().to_numpy().astype(np.int64))
        yield pa.record_batch([pa.array([a for a, _ in links], pa.int64()), pa.array([b for _, b in links], pa.int64())], ["u", "v"])


def roots(prints: DataFrame, docs: DataFrame) -> DataFrame:
    """node, root: components of the classes whose sets are similar."""
    spread = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    classes = materialise(prints.groupBy("fp").agg(*[F.first(c).alias(c) for c in CLASS[1:]]), "classes")
    keys = classes.select("fp", "bits", "codes").repartition(spread).mapInArrow(_keys, "key int, fp long, bits long")
    found = keys.repartition("key").sortWithinPartitions("key").mapInArrow(_candidates, "key int, u long, v long")
    found = materialise(found, "candidates")
    large = found.filter("v is null").select("key", F.col("u").alias("fp")).join(classes.drop("codes"), "fp")
    trees = large.repartition("key").sortWithinPartitions("key").mapInArrow(_trees, "key int, fp long, bits long, size long, sketch binary, parent long")
    trees = materialise(trees, "trees")
    edges = trees.filter("parent is not null").select(F.least("fp", "parent").alias("u"), F.greatest("fp", "parent").alias("v"))
    pairs = materialise(found.filter("v is not null").select("u", "v").unionByName(edges).distinct(), "pairs")
    need = pairs.select(F.col("u").alias("fp")).unionByName(pairs.select(F.col("v").alias("fp"))).distinct()
    texts = pick(docs.select("doc_id", "text"), first_of(prints.join(need, "fp", "left_semi"), "fp"))
    sets = materialise(texts.mapInArrow(_sets, "fp long, shingles array<long>"), "sets")
    a = sets.select(F.col("fp").alias("u"), F.col("shingles").alias("a"))
    b = sets.select(F.col("fp").alias("v"), F.col("shingles").alias("b"))
    both = F.size(F.array_intersect("a", "b"))
    near = pairs.join(a, "u").join(b, "v").filter(LEAST[1] * both >= LEAST[0] * (F.size("a") + F.size("b") - both)).select("u", "v")
    near = materialise(near, "links")
    found = components(near)
    if trees.isEmpty():
        return found
    rooted = trees.drop("parent").join(found, F.col("fp") == F.col("node"), "left").select("key", "fp", "bits", "size", "sketch", F.coalesce("root", "fp").alias("root"))
    mixed = rooted.repartition("key").sortWithinPartitions("key").mapInArrow(_mixed, "key int, fp long")
    dense = mixed.join(sets, "fp").select("key", "fp", "shingles").repartition("key").sortWithinPartitions("key")
    more = materialise(dense.mapInArrow(_forests, "u long, v long").distinct(), "more")
    if more.isEmpty():
        return found
    return components(more.unionByName(found.select(F.col("node").alias("u"), F.col("root").alias("v"))))


def keep_one(docs: DataFrame) -> DataFrame:
    """One document of each component of similar texts, with all its columns."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    marked = docs.select("doc_id", "text", F.xxhash64("text").alias("mark"))
    prints = materialise(marked.mapInArrow(_prints, f"doc_id {kind}, mark long, {CLASS_TYPES}"), "prints")
    rows = prints.select("doc_id", "mark", "fp").join(roots(prints, docs), F.col("fp") == F.col("node"), "left").select("doc_id", "mark", F.coalesce("root", "fp").alias("root"))
    return pick(docs, materialise(first_of(rows, "root"), "first"))
