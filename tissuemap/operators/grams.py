"""Hashed letter 3-grams of whole texts, counted in the task that reads them."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa

CODES = 256
#: Characters that are counted at once, at least one text.
CHARACTERS = 1 << 20
#: Entries of a table of all 3-grams of an alphabet; larger alphabets are sorted.
TABLE = 1 << 24


@cache
def _lower(c: int) -> int:
    """Lower case of one character as one character."""
    low = chr(c).lower()
    return ord(low[0])


@cache
def _code(gram: str) -> int:
    """The first four hex digits of the digest, modulo ``CODES``."""
    return hashlib.md5(gram.encode("utf-8", "surrogatepass")).digest()[1]


def count_texts(texts: list[str]) -> np.ndarray:
    """Texts x CODES: 3-grams of each text by their code."""
    n = np.array([len(t) for t in texts])
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    found, at = np.unique(points, return_inverse=True)
    low = np.array([_lower(int(c)) for c in found], np.int64)
    alphabet, small = np.unique(low, return_inverse=True)
    at = small[at]
    a = len(alphabet)
    ends = np.cumsum(n)
    # the last two characters of a text begin no gram
    start = np.ones(len(at), bool)
    for back in (1, 2):
        start[(ends - back)[n >= back]] = False
    first = np.flatnonzero(start)
    key = (at[first] * a + at[first + 1]) * a + at[first + 2]
    spell = lambda k: "".join(chr(alphabet[i]) for i in (k // (a * a), k // a % a, k % a))
    if a**3 <= TABLE:
        table = np.zeros(a**3, np.int64)
        table[key] = 1
        for k in np.flatnonzero(table).tolist():
            table[k] = _code(spell(k))
        code = table[key]
    else:
        kinds, where = np.unique(key, return_inverse=True)
        code = np.array([_code(spell(k)) for k in kinds.tolist()], np.int64)[where]
    owner = np.repeat(np.arange(len(texts)), np.maximum(n - 2, 0))
    return np.bincount(owner * CODES + code, minlength=len(texts) * CODES).reshape(len(texts), CODES)


def counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """id, n (CODES whole numbers of 64 bits) of every text of three characters or more."""
    for b in batches:
        ids, texts, size = [], [], 0
        for i, t in zip(b.column("id"), b.column("text"), strict=True):
            text = t.as_py()
            if text is None or len(text) < 3:
                continue
            ids.append(i.as_py())
            texts.append(text)
            size += len(text)
            if size >= CHARACTERS:
                yield _rows(ids, texts)
                ids, texts, size = [], [], 0
        if ids:
            yield _rows(ids, texts)


def _rows(ids: list, texts: list[str]) -> pa.RecordBatch:
    return pa.record_batch([pa.array(ids, pa.int64()), pa.array([x.tobytes() for x in count_texts(texts)], pa.binary())], ["id", "n"])


def units(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """id, x: the counts of an id added up, of length one."""
    for b in batches:
        if not b.num_rows:
            continue
        lists = b.column("n")
        rows = np.frombuffer(b"".join(lists.flatten().to_pylist()), np.int64).reshape(-1, CODES)
        starts = np.concatenate(([0], np.cumsum(lists.value_lengths().to_numpy())[:-1])).astype(np.int64)
        x = np.add.reduceat(rows, starts, axis=0).astype(float)
        x /= np.sqrt((x * x).sum(axis=1, keepdims=True))
        yield pa.record_batch([b.column("id"), pa.ListArray.from_arrays(np.arange(0, x.size + 1, CODES, dtype=np.int32), pa.array(x.ravel()))], ["id", "x"])
