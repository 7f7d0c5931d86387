"""Best-fit packing of token sequences by bin completion.

Texts become token ids and then pieces of at most ``SIZE`` tokens. Lengths are
whole numbers up to SIZE, so the packing problem is fully described by how many
pieces there are of each length: a table of SIZE numbers, which the driver solves
whatever the input. Bin completion takes the largest length left, enumerates the
undominated ways to fill the rest of its sequence (a filling is dominated when
another one uses a longer piece in place of shorter ones that together are no
longer), and branches over them and over how often each is used, depth first,
least waste first. A branch ends once the bound on what is left cannot beat the
incumbent, which is best-fit at first.

The search is complete; ``BUDGET`` bounds its steps, and :class:`Solution` says
whether the result is proven to be the optimum or the steps ran out before. Only
the proof depends on it: every piece is placed in any case.

The plan is a list of patterns with multiplicities. Pieces find their place by
their rank within their length, which is counted in slices and never sorted as a
whole. Ids themselves are not shuffled.

Defined results: a null or empty text is the end token alone; repeated rows are
packed each; order among equal lengths follows a hash of (doc_id, piece), then
the ids; an empty table gives an empty result.
"""

from __future__ import annotations

import json
import logging
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import regex
import tiktoken
import tokenizers
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise

SIZE = 1024
END = 2
SLICES = 128
#: Steps of the search: nodes visited and pieces tried.
BUDGET = 200_000
#: Texts with a longer run of blanks go to the reference engine, as the fast one
#: backtracks over such runs and gives up at a million.
LONG_BLANK = 100_000
#: Pre-tokenisation of the byte-level vocabulary (fixed values).
PIECES = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


#: How often each pattern of lengths is used.
Plan = list[tuple[tuple[int, ...], int]]


@dataclass(frozen=True)
class Solution:
    """A packing, the bound below it, whether it is proven optimal, steps taken."""

    plan: Plan
    floor: int
    proven: bool
    steps: int

    @property
    def sequences(self) -> int:
        return _sequences(self.plan)


@lru_cache(1)
def encoder(path: str) -> tiktoken.Encoding:
    """The vocabulary of a byte-level BPE file, in a fast engine.

    In such files bytes stand as printable characters; ids follow merge order, so
    they double as ranks. Special tokens keep their ids and are found in texts.
    """
    spec = json.load(open(path, encoding="utf-8"))
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    chars = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in plain)}
    special = {t["content"]: t["id"] for t in spec.get("added_tokens", ())}
    ranks = {bytes(chars[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in special}
    return tiktoken.Encoding("byte_bpe", pat_str=PIECES, mergeable_ranks=ranks, special_tokens=special)


@lru_cache(1)
def _reference(path: str) -> tokenizers.Tokenizer:
    return tokenizers.Tokenizer.from_file(path)


def token_ids(text: str | None, path: str) -> list[int]:
    """The ids of one text, the same from both engines."""
    if not text:
        return []
    if len(text) > LONG_BLANK and any(m.end() - m.start() > LONG_BLANK for m in regex.finditer(r"\s++", text)):
        return _reference(path).encode(text, add_special_tokens=False).ids
    return encoder(path).encode(text, allowed_special="all")


def _pieces(path: str, size: int, end: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            source, piece, start, length, crc = [], [], [], [], []
            for i, text in enumerate(b.column("text").to_pylist()):
                ids = [*token_ids(text, path), end]
                raw = np.array(ids, "<u4").tobytes()
                n = len(ids)
                edges = [0, *range((n - 1) % size + 1, n + 1, size)]
                for k, (a, z) in enumerate(zip(edges, edges[1:], strict=False)):
                    source.append(i)
                    piece.append(k)
                    start.append(a)
                    length.append(z - a)
                    crc.append(zlib.crc32(memoryview(raw)[4 * a : 4 * z]))
            ids = b.column("doc_id").take(pa.array(source, pa.int32()))
            yield pa.record_batch(
                [ids, pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())],
                ["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    return run


def pieces(docs: DataFrame, path: str, size: int = SIZE, end: int = END) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32. Only a document's first piece may
    be shorter than ``size``."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(_pieces(path, size, end), f"doc_id {kind}, piece int, start long, length long, ids_crc32 long")


def lower_bound(counts: np.ndarray, size: int) -> int:
    """Sequences that any packing needs: by volume, and, for each cut, those that
    hold long pieces plus the volume that does not fit beside them."""
    half = size // 2
    number = np.concatenate(([0], np.cumsum(counts)))  # number[k]: pieces shorter than k
    volume = np.concatenate(([0], np.cumsum(counts * np.arange(len(counts)))))
    cut = np.arange(half + 1)
    above = size - cut + 1
    big = number[-1] - number[above]
    mid, mid_volume = number[above] - number[half + 1], volume[above] - volume[half + 1]
    over = volume[half + 1] - volume[cut] - (mid * size - mid_volume)
    return int(max(-(-volume[-1] // size), (big + mid + np.maximum(0, -(-over // size))).max()))


class Spent(Exception):
    """The search has used up its steps."""


class _Steps:
    def __init__(self, most: int) -> None:
        self.left = most

    def take(self) -> None:
        self.left -= 1
        if self.left < 0:
            raise Spent


def dominated(filling: tuple[int, ...], left: np.ndarray, room: int) -> bool:
    """Whether some piece outside the filling can replace pieces of it that are
    together no longer, and the whole still fits.

    If any filling dominates this one, such a single exchange exists: one of its
    pieces covers some of ours, and what else it holds is no shorter than the rest.
    """
    slack = room - sum(filling)
    used = Counter(filling)

    def reaches(pieces, targets: int) -> bool:
        sums = 1
        for v in pieces:
            sums |= sums << v
        width = 0  # sums that fall short by up to ``slack`` count as well
        while width < slack:
            step = min(width + 1, slack - width)
            sums |= sums << step
            width += step
        return bool(sums & targets)

    spare = [v for v in np.flatnonzero(left[: room + 1]).tolist() if v and left[v] > used[v]]
    if reaches(filling, sum(1 << v for v in spare if not used[v])):
        return True
    return any(reaches([x for x in filling if x != v], 1 << v) for v in spare if used[v])


def fillings(left: np.ndarray, room: int, waste: int, steps: _Steps) -> Iterator[tuple[int, ...]]:
    """All undominated ways to fill ``room`` with at most ``waste`` left over, least
    waste first, then longer pieces first. A single exact piece dominates the rest.

    Which sums the shorter pieces can make is held as bits, so that the way to a
    filling of a given sum never leads astray.
    """
    have = [v for v in np.flatnonzero(left[: room + 1]).tolist() if v][::-1]
    if have and have[0] == room:
        yield (room,)
        return
    full = (1 << room + 1) - 1
    reach = [1] * (len(have) + 1)
    for i in range(len(have) - 1, -1, -1):
        v, bits, more, copies = have[i], reach[i + 1], min(int(left[have[i]]), room // have[i]), 1
        while more > 0:
            bits |= bits << v * min(copies, more) & full
            more -= copies
            copies *= 2
        reach[i] = bits

    def exact(at: int, target: int) -> Iterator[tuple[int, ...]]:
        if not target:
            yield ()
            return
        for i in range(at, len(have)):
            steps.take()
            v = have[i]
            if v <= target:
                for n in range(min(int(left[v]), target // v), 0, -1):
                    if reach[i + 1] >> target - n * v & 1:
                        for rest in exact(i + 1, target - n * v):
                            yield (v,) * n + rest
                if v == target:
                    return
            if not reach[i + 1] >> target & 1:
                return

    for short in range(min(waste, room) + 1):
        if reach[0] >> room - short & 1:
            for filling in exact(0, room - short):
                steps.take()
                if not dominated(filling, left, room):
                    yield filling


def best_fit(counts: np.ndarray, size: int) -> Plan:
    """Best-fit decreasing over counts: the first incumbent. Each sequence takes
    the longest piece that still fits, again and again."""
    left = counts.astype(np.int64).copy()
    plan = []
    while left[1:].any():
        whole, room = [], size
        need = np.zeros_like(left)
        while True:
            fit = np.flatnonzero(left[: room + 1] > need[: room + 1])
            fit = fit[fit > 0]
            if not len(fit):
                break
            v = int(fit[-1])
            whole.append(v)
            need[v] += 1
            room -= v
        used = np.flatnonzero(need)
        times = int((left[used] // need[used]).min())
        left -= need * times
        plan.append((tuple(whole), times))
    return plan


def _sequences(plan: Plan) -> int:
    return sum(times for _, times in plan)


class _Node:
    """A state of the search: what is left, and the ways to go on from it.

    The sequences around equal longest pieces are told apart only by how often
    each filling occurs. A child therefore takes the next filling a number of
    times, most first, and never again one that was passed over (``barred``).
    """

    def __init__(self, left: np.ndarray, done: int, barred: tuple, waste: int, steps: _Steps) -> None:
        self.left, self.done, self.steps = left, done, steps
        self.room = 0
        top = np.flatnonzero(left)
        self.big = int(top[-1]) if len(top) and top[-1] else 0
        self.barred = barred if barred and barred[0] == self.big else (self.big, ())
        if self.big:
            rest = left.copy()
            rest[self.big] -= 1
            self.room = len(left) - 1 - self.big
            self.ways = fillings(rest, self.room, waste, steps)
        self.pending: list[tuple[tuple[int, ...], int]] = []
        self.passed: list[tuple[int, ...]] = []

    def next(self) -> tuple[tuple[int, ...], int, np.ndarray, tuple] | None:
        """The next child: pattern, times, what it leaves, what it bars."""
        self.steps.take()
        filling = next((f for f in self.ways if f not in self.barred[1]), None) if self.ways is not None else None
        if filling is not None:
            whole = (self.big, *filling)
            need = np.bincount(whole, minlength=len(self.left))
            used = np.flatnonzero(need)
            times = int((self.left[used] // need[used]).min())
            bar = (*self.passed, filling)
            self.passed.append(filling)
            if times > 1 and filling != (self.room,):  # an exact piece has no rival
                self.pending.append((whole, times - 1, bar))
            return whole, times, self.left - need * times, (self.big, self.barred[1] + bar)
        self.ways = None
        if not self.pending:
            return None
        whole, times, bar = self.pending.pop()
        if times > 1:
            self.pending.append((whole, times - 1, bar))
        return whole, times, self.left - np.bincount(whole, minlength=len(self.left)) * times, (self.big, self.barred[1] + bar)


def solve(counts: np.ndarray, size: int = SIZE, budget: int = BUDGET) -> Solution:
    """Branch and bound, depth first, with best-fit as the first incumbent.

    A branch ends when the sequences so far and the bound on the rest are no
    fewer than the incumbent's. After ``budget`` steps the incumbent is returned
    with ``proven`` unset, unless it meets the bound.
    """
    counts = np.asarray(counts[: size + 1], np.int64).copy()
    counts[0] = 0
    best, floor, steps = best_fit(counts, size), lower_bound(counts, size), _Steps(budget)
    fewest = _sequences(best)
    volume = int((counts * np.arange(size + 1)).sum())
    stack: list[_Node] = []
    plan: Plan = []

    def push(left: np.ndarray, done: int, barred: tuple) -> None:
        # what all sequences of a better plan may leave empty, less what these do
        taken = volume - int((left * np.arange(size + 1)).sum())
        stack.append(_Node(left, done, barred, (fewest - 1) * size - volume - (done * size - taken), steps))

    try:
        if fewest > floor:
            push(counts, 0, ())
        while stack:
            node = stack[-1]
            child = node.next() if node.big else None
            if child is None:
                stack.pop()
                if stack:
                    plan.pop()
                continue
            whole, times, left, barred = child
            done = node.done + times
            if done + lower_bound(left, size) >= fewest:
                continue
            plan.append((whole, times))
            if not left.any():
                best, fewest = list(plan), done
                plan.pop()
                if fewest <= floor:
                    break
                continue
            push(left, done, barred)
    except Spent:
        return Solution(best, floor, fewest <= floor, budget)
    return Solution(best, floor, True, budget - max(steps.left, 0))


def _places(plan: Plan) -> dict[int, list[tuple[int, int, int, int]]]:
    """Per length: (first rank, first sequence, times, offset) of each slot."""
    out: dict[int, list[tuple[int, int, int, int]]] = {}
    taken: dict[int, int] = {}
    base = 0
    for whole, times in plan:
        offset = 0
        for v in whole:
            out.setdefault(v, []).append((taken.get(v, 0), base, times, offset))
            taken[v] = taken.get(v, 0) + times
            offset += v
        base += times
    return out


def _assign(places: dict[int, list[tuple[int, int, int, int]]]):
    tables = {v: np.array(x) for v, x in places.items()}

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            seq, off = np.zeros(len(b), np.int64), np.zeros(len(b), np.int64)
            length, rank = b["length"].to_numpy(), b["rank"].to_numpy()
            for v in np.unique(length).tolist():
                mine = np.flatnonzero(length == v)
                t = tables[v]
                slot = np.searchsorted(t[:, 0], rank[mine], "right") - 1
                seq[mine] = t[slot, 1] + rank[mine] - t[slot, 0]
                off[mine] = t[slot, 3]
            yield b.drop(columns="rank").assign(sequence_id=seq, offset=off)

    return run


def pack(docs: DataFrame, path: str, size: int = SIZE, end: int = END, budget: int = BUDGET) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    cut = materialise(pieces(docs, path, size, end), "pieces")
    # at most ``size`` rows come to the driver
    counts = np.zeros(size + 1, np.int64)
    for row in cut.groupBy("length").count().collect():
        counts[row["length"]] = row["count"]
    found = solve(counts, size, budget)
    if not found.proven:
        logging.getLogger(__name__).warning("packing: %d sequences, at least %d needed; not proven after %d steps", found.sequences, found.floor, found.steps)
    places = _places(found.plan)
    cut = cut.withColumn("_slice", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(SLICES)).cast("int"))
    sums = cut.groupBy("length", "_slice").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select("length", "_slice", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("_first"))
    inside = F.row_number().over(Window.partitionBy("length", "_slice").orderBy("doc_id", "piece", "ids_crc32"))
    # at most size * SLICES rows are broadcast
    ranked = cut.withColumn("_at", inside).join(F.broadcast(starts), ["length", "_slice"])
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("_first") + F.col("_at") - 1).alias("rank"))
    return ranked.mapInPandas(_assign(places), f"doc_id {kind}, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
