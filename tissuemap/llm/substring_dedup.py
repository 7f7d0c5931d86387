"""Substring deduplication over prefix-partitioned suffix trees of words.

Two suffixes whose first ``WINDOW`` words agree pass through one node of a suffix
tree at that depth; all but the earliest suffix below a node are repeats. Merged,
the repeated windows are the maximal repeats.

Which suffixes stand in the tree. Of the 13 word 8-grams in a window the one with
the least hash, the leftmost of equals, is its anchor. Equal windows have their
anchors at the same place, so a tree of the suffixes that begin at anchors, one in
seven, decides all windows: a window that begins ``o`` words before its anchor
repeats if two anchored suffixes agree in 20 - o words to the right and o words to
the left. The windows of one anchor travel as one row with their words.

Partition. Anchored suffixes are grouped by a prefix of eight words. Prefixes are
counted first. One that occurs once has a leaf below it and no node, and is left
out. One that occurs more often than a group may hold is lengthened to the depth
that decides, where each group is a single node, and a node needs no task of its
own: its earliest suffix is a minimum, added up on the map side.

In a group, suffixes are sorted by the words to the right of the anchor, and the
words shared with the neighbour give the nodes at every depth; the same is done to
the left. Words are compared themselves, not only their hashes.

Of equal windows in one chunk of documents only the earliest is sent on, the rest
are repeats at once. A passage that a third of all documents hold thus reaches the
shuffle once per chunk, not once per document.

Defined results: a null or blank text has no words; a text below 20 words keeps
all; equal rows (same id and text) count as one document, each keeping what the
document keeps; a null id comes after all others; documents that share an id are
ordered by a hash of the text, and ids that are not whole numbers by their hash;
an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from hashlib import sha256

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import materialise, run_starts, text_bytes

WINDOW = 20
GRAM = 8
#: Words that a window may hold before its anchor.
LEAD = WINDOW - GRAM
#: Words handled at once in a task.
CHUNK = 600_000
#: Rows that a group may hold: this many, or a ``HOT``-th of all rows if that is
#: more, so that no more than HOT prefixes are lengthened.
GROUP, HOT = 4096, 2_000_000
#: Rows of whole groups that are solved together.
BATCH = 20_000
#: Bits of the filter of prefixes that occur twice: sixteen for each of them. Where
#: that exceeds the second figure (32 MB), suffixes are joined to the prefixes.
FILTER_BITS = (1 << 20, 1 << 28)
BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
LAST = (1 << 63) - 1


@lru_cache(1)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    inverse = np.uint64(pow(int(BASE), -1, 1 << 64))
    one = np.ones(1, np.uint64)
    up = np.concatenate([one, np.cumprod(np.full(n, BASE, np.uint64), dtype=np.uint64)])
    down = np.concatenate([one, np.cumprod(np.full(n, inverse, np.uint64), dtype=np.uint64)])
    return up, down


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _rolling(h: np.ndarray, width: int) -> np.ndarray:
    """Digest of each run of ``width`` word hashes, by prefix sums modulo 2^64."""
    size = 1 << max(CHUNK, len(h) + 1).bit_length()
    up, down = _powers(size)
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * up[: len(h)], dtype=np.uint64)])
    return _mix((total[width:] - total[:-width]) * down[: len(h) - width + 1])


def _least_of(x: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Minimum of each run of ``width`` neighbours, and its leftmost place."""
    least, at, have = x, np.arange(len(x)), 1
    while have < width:
        step = min(have, width - have)
        right = least[step:] < least[:-step]
        at = np.where(right, at[step:], at[:-step])
        least, have = np.minimum(least[:-step], least[step:]), have + step
    return least, at


class _Chunk:
    """Words of some documents end to end, and their windows."""

    def __init__(self) -> None:
        self.words: list[bytes] = []
        self.docs: list[tuple[int, int, int]] = []
        self.starts: list[np.ndarray] = []  # of the runs that may repeat, if known

    def add(self, doc: int, mark: int, words: list[bytes], starts: list[int] | None) -> None:
        if starts is not None:
            self.starts.append(np.array(starts, np.int64) | len(self.docs) << 32)
        self.docs.append((doc, mark, len(words)))
        self.words += words

    def windows(self) -> _Windows:
        digest = xxhash.xxh64_digest
        h = np.frombuffer(b"".join([digest(w) for w in self.words]), np.uint64)
        n = np.array([d[2] for d in self.docs])
        at = np.arange(len(h)) - np.repeat(np.cumsum(n) - n, n)
        good = np.flatnonzero(at[: len(h) - WINDOW + 1] + WINDOW <= np.repeat(n, n)[: len(h) - WINDOW + 1])
        prefix, anchor = _least_of(_rolling(h, GRAM), LEAD + 1)
        who = np.repeat(np.arange(len(n)), n)[good]
        doc, mark = (np.array([d[i] for d in self.docs], np.int64)[who] for i in (0, 1))
        return _Windows(h, good, doc, mark, at[good].astype(np.int32), prefix[good], anchor[good], _rolling(h, WINDOW)[good], who)


class _Windows:
    """Parallel arrays over the windows of a chunk, in reading order: place in the
    chunk, document, start in it, hash of the prefix at the anchor, the anchor's
    place, digest of the window, number of the document in the chunk; and the hashes
    of all words."""

    def __init__(self, h, place, doc, mark, start, prefix, anchor, digest, who) -> None:
        self.h = h
        self.columns = (place, doc, mark, start, prefix, anchor, digest, who)
        self.place, self.doc, self.mark, self.start, self.prefix, self.anchor, self.digest, self.who = self.columns

    def take(self, which: np.ndarray) -> _Windows:
        return _Windows(self.h, *(c[which] for c in self.columns))

    def runs(self) -> np.ndarray:
        """Where a new run begins: another anchor, or a gap."""
        if not len(self.place):
            return np.zeros(0, np.int64)
        same = (self.anchor[1:] == self.anchor[:-1]) & (self.place[1:] == self.place[:-1] + 1)
        return np.concatenate(([0], np.flatnonzero(~same) + 1))

    def first_and_later(self) -> tuple[_Windows, _Windows]:
        """Of equal windows the earliest, and the others; windows of equal rows
        (same document and start) are one, a copy is in neither."""
        order = np.lexsort((self.start, self.mark, self.doc, self.digest, self.prefix))
        s = self.take(order)
        new = np.ones(len(order), bool)
        new[1:] = (s.prefix[1:] != s.prefix[:-1]) | (s.digest[1:] != s.digest[:-1])
        head = np.maximum.accumulate(np.where(new, np.arange(len(order)), 0))
        rest = np.flatnonzero(~new)
        words = np.lib.stride_tricks.sliding_window_view(self.h, WINDOW)
        for lo in range(0, len(rest), 50_000):  # equal digests of unequal words
            part = rest[lo : lo + 50_000]
            new[part] = (words[s.place[part]] != words[s.place[head[part]]]).any(axis=1)
        same = (s.doc == s.doc[head]) & (s.mark == s.mark[head]) & (s.start == s.start[head])
        return self.take(np.sort(order[new])), self.take(order[~new & ~same])


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[_Chunk]:
    chunk = _Chunk()
    for b in batches:
        docs, marks = b.column("doc").to_numpy(), b.column("mark").to_numpy()
        starts = b.column("starts").to_pylist() if "starts" in b.schema.names else [None] * b.num_rows
        for doc, mark, text, some in zip(docs.tolist(), marks.tolist(), text_bytes(b.column("text")), starts, strict=True):
            words = text.split()
            if len(words) >= WINDOW:
                chunk.add(doc, mark, words, some)
                if len(chunk.words) >= CHUNK:
                    yield chunk
                    chunk = _Chunk()
    if chunk.words:
        yield chunk


def _prefixes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """How often each prefix begins an anchored suffix. Equal windows have places
    of their own, so their anchors have too, and count one by one."""
    for chunk in _chunks(batches):
        w = chunk.windows()
        p = np.sort(w.prefix[w.runs()])
        at = run_starts(p)
        yield pa.record_batch([pa.array(p[at].view(np.int64)), pa.array(np.diff(np.append(at, len(p))).astype(np.int32))], ["prefix", "n"])


def _run_starts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Prefix and place of every anchored suffix."""
    for chunk in _chunks(batches):
        w = chunk.windows()
        at = w.runs()
        yield pa.record_batch([pa.array(w.prefix[at].view(np.int64)), pa.array(w.doc[at]), pa.array(w.mark[at]), pa.array(w.start[at])], ["prefix", "doc", "mark", "start"])


def _slots(prefix: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    m = np.uint64(bits - 1)
    return (prefix & m).astype(np.int64), ((prefix >> np.uint64(32)) & m).astype(np.int64)


def _spans(doc, mark, start) -> list[pa.Array]:
    """Windows to remove as runs: doc, mark, start, count."""
    order = np.lexsort((start, mark, doc))
    doc, mark, start = doc[order], mark[order], start[order]
    new = np.ones(len(doc), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (mark[1:] != mark[:-1]) | (start[1:] != start[:-1] + 1)
    at = np.flatnonzero(new)
    return [pa.array(doc[at]), pa.array(mark[at]), pa.array(start[at]), pa.array(np.diff(np.append(at, len(doc))).astype(np.int32))]


SUFFIX = "prefix long, doc long, mark long, start int, n int, at int, words binary"
NODE = "words binary, doc long, mark long, start int, n int"


def _suffixes(bits, hot):
    """Anchored suffixes for the groups, and spans that are settled: these have no
    words and a prefix made of the document, which deals them out. Without ``bits``
    the documents bring the starts of the runs whose prefix occurs twice."""

    def may_repeat(chunk: _Chunk, w: _Windows) -> np.ndarray:
        if bits is None:
            at = w.runs()
            known = np.isin(w.start[at] | w.who[at] << 32, np.concatenate(chunk.starts))
            return np.repeat(known, np.diff(np.append(at, len(w.place))))
        held = np.frombuffer(bits.value, np.uint8)
        a, b = _slots(w.prefix, len(held) * 8)
        return (held[a >> 3] >> (a & 7) & held[b >> 3] >> (b & 7) & 1).astype(bool)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often = np.frombuffer(hot.value, np.uint64)
        names = [c.split()[0] for c in SUFFIX.split(", ")]
        for chunk in _chunks(batches):
            w = chunk.windows()
            live = may_repeat(chunk, w)
            live[live] = ~np.isin(w.prefix[live], often)
            if not live.any():
                continue
            first, later = w.take(live).first_and_later()
            if len(later.place):
                spans = _spans(later.doc, later.mark, later.start)
                dealt = spans[0].to_numpy().view(np.uint64) * BASE
                k = len(spans[0])
                yield pa.record_batch([pa.array(dealt.view(np.int64)), *spans, pa.nulls(k, pa.int32()), pa.nulls(k, pa.binary())], names)
            at = first.runs()
            n = np.diff(np.append(at, len(first.place)))
            place = first.place[at]
            text = [b" ".join(chunk.words[x : x + y]) for x, y in zip(place.tolist(), (n + WINDOW - 1).tolist(), strict=True)]
            columns = [first.prefix[at].view(np.int64), first.doc[at], first.mark[at], first.start[at], n.astype(np.int32), (first.anchor[at] - place).astype(np.int32)]
            yield pa.record_batch([*map(pa.array, columns), pa.array(text, pa.binary())], names)

    return run


def _long_prefixes(hot):
    """Windows whose prefix is lengthened, with all their words; spans that are
    settled have no words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often = np.frombuffer(hot.value, np.uint64)
        names = [c.split()[0] for c in NODE.split(", ")]
        for chunk in _chunks(batches):
            w = chunk.windows()
            first, later = w.take(np.isin(w.prefix, often)).first_and_later()
            spans = _spans(later.doc, later.mark, later.start)
            yield pa.record_batch([pa.nulls(len(spans[0]), pa.binary()), *spans], names)
            text = [b" ".join(chunk.words[x : x + WINDOW]) for x in first.place.tolist()]
            yield pa.record_batch([pa.array(text, pa.binary()), pa.array(first.doc), pa.array(first.mark), pa.array(first.start), pa.array(np.ones(len(text), np.int32))], names)

    return run


def _nodes(key: np.ndarray, words: np.ndarray) -> list[np.ndarray]:
    """Node of each row at depth 0, 1, ... of the tree of ``words`` below ``key``:
    sorted neighbours share a node as far as their words agree."""
    depth = words.shape[1]
    order = np.lexsort((*words.T[::-1], key))
    equal = np.ones((len(key), depth + 1), bool)
    equal[1:, 0] = key[order][1:] == key[order][:-1]
    equal[1:, 1:] = words[order][1:] == words[order][:-1]
    shared = np.where(equal.all(axis=1), depth + 1, equal.argmin(axis=1))
    shared[0] = 0
    out = []
    for d in range(depth + 1):
        node = np.empty(len(key), np.int64)
        node[order] = np.cumsum(shared <= d)
        out.append(node)
    return out


def repeated(prefix, doc, mark, start, n, at, lines: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """doc, mark and start of all windows that repeat an earlier one, in whole
    groups of anchored suffixes."""
    anchor = start + at
    order = np.lexsort((anchor, mark, doc))  # the order of windows at any one lead
    prefix, doc, mark, start, n, at, anchor = (x[order] for x in (prefix, doc, mark, start, n, at, anchor))
    ids: dict[bytes, int] = {}
    flat = np.array([ids.setdefault(w, len(ids)) for i in order.tolist() for w in lines[i].split(b" ")], np.int32)
    size = n + WINDOW - 1
    place = np.cumsum(size) - size + at
    key = np.unique(prefix, return_inverse=True)[1]
    right = np.stack([np.where(at + j < size, flat[np.minimum(place + j, len(flat) - 1)], -1) for j in range(WINDOW)], axis=1)
    left = np.stack([np.where(at >= j, flat[np.maximum(place - j, 0)], -1) for j in range(1, LEAD + 1)], axis=1)
    after, before = _nodes(key, right), _nodes(key, left)
    out = []
    for lead in range(LEAD + 1):
        mine = np.flatnonzero((at >= lead) & (at - lead < n))
        node = after[WINDOW - lead][mine] * (len(key) + 1) + before[lead][mine]
        sort = np.argsort(node, kind="stable")
        mine, node = mine[sort], node[sort]
        new = np.ones(len(mine), bool)
        new[1:] = node[1:] != node[:-1]
        head = mine[np.maximum.accumulate(np.where(new, np.arange(len(mine)), 0))]
        copy = (doc[mine] == doc[head]) & (mark[mine] == mark[head]) & (anchor[mine] == anchor[head])
        later = mine[~copy]
        out.append((doc[later], mark[later], anchor[later] - lead))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Spans of the repeats of each group; rows are sorted by prefix."""
    names = ["doc", "mark", "start", "n"]
    held: list[pa.RecordBatch] = []
    rows, need = 0, BATCH

    def solved(group: pa.Table) -> pa.RecordBatch:
        c = {x: group.column(x).to_numpy() for x in ("prefix", "doc", "mark", "start", "n", "at")}
        return pa.record_batch(_spans(*repeated(**c, lines=group.column("words").to_pylist())), names)

    for b in batches:
        settled = b.column("words").is_null()
        yield b.filter(settled).select(names)
        b = b.filter(pc.invert(settled))
        held.append(b)
        rows += b.num_rows
        if rows >= need:
            t = pa.Table.from_batches(held)
            prefix = t.column("prefix").to_numpy()
            last = int(np.searchsorted(prefix, prefix[-1]))
            if last:
                yield solved(t.slice(0, last))
            held, rows = t.slice(last).to_batches(), len(prefix) - last
            need = max(BATCH, 2 * rows)
    if rows:
        yield solved(pa.Table.from_batches(held))


def _filter_of(shared: DataFrame, bits: int) -> bytes:
    """Bit filter of the prefixes in ``shared``."""
    slot = F.explode(F.array(F.col("prefix").bitwiseAND(F.lit(bits - 1)), F.shiftrightunsigned("prefix", 32).bitwiseAND(F.lit(bits - 1))))
    words = shared.select(slot.alias("slot")).groupBy(F.shiftright("slot", 6).alias("at"))
    rows = words.agg(F.bit_or(F.expr("shiftleft(1L, cast(slot & 63 as int))")).alias("bits")).toArrow()
    out = np.zeros(bits // 64, np.int64)
    out[rows.column("at").to_numpy()] = rows.column("bits").to_numpy()
    return out.tobytes()


def _with_starts(body: DataFrame, shared: DataFrame) -> DataFrame:
    """The documents that have prefixes of ``shared``, and where: two shuffles of
    numbers and one of these documents, whatever the number of prefixes."""
    runs = body.mapInArrow(_run_starts, "prefix long, doc long, mark long, start int")
    kept = runs.join(shared.select("prefix"), "prefix", "left_semi")
    return body.join(kept.groupBy("doc", "mark").agg(F.collect_set("start").alias("starts")), ["doc", "mark"])


def _lengthened(body: DataFrame, hot) -> DataFrame:
    """Spans below prefixes that are lengthened: a group is one node, all its
    suffixes but the earliest are repeats."""
    rows = materialise(body.mapInArrow(_long_prefixes(hot), NODE), "longprefixes")
    here = F.struct("doc", "mark", "start")
    nodes = rows.filter("words is not null")
    first = materialise(nodes.groupBy("words").agg(F.min(here).alias("first")), "nodes")
    later = nodes.join(first, "words").filter(F.col("first") < here)
    return later.select("doc", "mark", "start", "n").unionByName(rows.filter("words is null").drop("words"))


def repeats(docs: DataFrame, group: int = GROUP) -> DataFrame:
    """doc, mark, spans: the windows to remove of each document that has any."""
    context = docs.sparkSession.sparkContext
    body = _marked(docs).select("doc", "mark", "text")
    counted = body.mapInArrow(_prefixes, "prefix long, n int").groupBy("prefix").agg(F.sum("n").alias("n"))
    shared = materialise(counted.filter("n > 1"), "prefixes")
    count, rows = shared.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
    # at most HOT prefixes exceed the bound
    often = shared.filter(F.col("n") > max(group, rows // HOT)).select("prefix").toArrow().column("prefix").to_numpy()
    hot = context.broadcast(np.sort(often.view(np.uint64)).tobytes())
    bits = max(FILTER_BITS[0], 1 << (16 * count).bit_length())
    if bits <= FILTER_BITS[1]:
        given, held = body, context.broadcast(_filter_of(shared, bits))
    else:
        given, held = _with_starts(body, shared), None
    suffixes = given.mapInArrow(_suffixes(held, hot), SUFFIX).repartition("prefix").sortWithinPartitions("prefix")
    spans = suffixes.mapInArrow(_solve, "doc long, mark long, start int, n int")
    if len(often):
        spans = spans.unionByName(_lengthened(body, hot))
    return spans.groupBy("doc", "mark").agg(F.collect_set(F.struct("start", "n")).alias("spans"))


def _marked(docs: DataFrame) -> DataFrame:
    """doc and mark, by which documents are ordered and told apart: the id, and a
    hash of the text that is larger for rows without an id."""
    whole = isinstance(docs.schema["doc_id"].dataType, T.IntegralType)
    number = F.col("doc_id").cast("long") if whole else F.when(F.col("doc_id").isNotNull(), F.xxhash64("doc_id"))
    none = F.when(F.col("doc_id").isNull(), F.lit(1 << 62)).otherwise(F.lit(0))
    mark = F.shiftrightunsigned(F.xxhash64(F.coalesce("text", F.lit(""))), 2)
    return docs.withColumns({"doc": F.coalesce(number, F.lit(LAST)), "mark": mark.bitwiseOR(none)})


def _rewrite(with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n, removed, digest, text = [], [], [], []
            starts, counts = b.column("starts").to_pylist(), b.column("counts").to_pylist()
            for raw, at, count in zip(text_bytes(b.column("text")), starts, counts, strict=True):
                words = raw.split()
                n.append(len(words))
                if at:
                    edge = np.zeros(len(words) + 1, np.int64)
                    np.add.at(edge, np.array(at), 1)
                    np.add.at(edge, np.array(at) + np.array(count) + WINDOW - 1, -1)
                    gone = np.cumsum(edge[:-1]) > 0
                    words = [w for w, x in zip(words, gone.tolist(), strict=True) if not x]
                removed.append(n[-1] - len(words))
                kept = b" ".join(words)
                digest.append(sha256(kept).hexdigest())
                if with_text:
                    text.append(kept.decode() if removed[-1] else None)
            own = [pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(digest, pa.string())]
            names = ["n_words", "n_removed", "kept_sha256"]
            if with_text:
                yield pa.record_batch([b.column("_row"), *own, pa.array(text, pa.string())], ["_row", *names, "kept_text"])
            else:
                yield pa.record_batch([b.column("doc_id"), *own], ["doc_id", *names])

    return run


def _joined(docs: DataFrame, group: int, *more: str) -> DataFrame:
    spans = materialise(repeats(docs, group), "spans").select(F.col("doc").alias("_d"), F.col("mark").alias("_m"), F.col("spans.start").alias("starts"), F.col("spans.n").alias("counts"))
    body = _marked(docs)
    out = body.join(spans, (F.col("doc") == F.col("_d")) & (F.col("mark") == F.col("_m")), "left")
    return out.select("text", "starts", "counts", *more)


def dedup(docs: DataFrame, group: int = GROUP) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every document."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    out = _joined(docs.select("doc_id", "text"), group, "doc_id")
    return out.mapInArrow(_rewrite(False), f"doc_id {kind}, n_words long, n_removed long, kept_sha256 string")


def dedup_rows(docs: DataFrame, least: int = 1, group: int = GROUP) -> DataFrame:
    """The documents with repeated passages cut out, columns unchanged.

    A text that loses nothing stays as it is, white space included; a text that
    loses words is the kept words joined by spaces. Documents left with fewer
    than ``least`` words go if words were removed.
    """
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")
    body = docs.select("doc_id", "text", row)
    shape = T.StructType([body.schema["_row"], *T.StructType.fromDDL("n_words long, n_removed long, kept_sha256 string, kept_text string")])
    out = _joined(body, group, "_row").mapInArrow(_rewrite(True), shape)
    out = out.filter((F.col("n_removed") == 0) | (F.col("n_words") - F.col("n_removed") >= least))
    text = F.when(F.col("n_removed") > 0, F.col("kept_text")).otherwise(F.col("_row.text"))
    fixed = {"text": text} | ({"n_chars": F.when(F.col("n_removed") > 0, F.length("kept_text").cast("long")).otherwise(F.col("_row.n_chars"))} if "n_chars" in docs.columns else {})
    return out.select(*[fixed.get(c, F.col(f"_row.`{c}`")).alias(c) for c in docs.columns])
