"""Document quality by regularised quadratic discriminant analysis.

Each text becomes a vector of statistics, transformed towards bell shapes. Each
class is a normal distribution whose covariance is shrunk twice: towards the
pooled covariance, then towards its own diagonal. The score is the
logistic of the difference of the log densities (Mahalanobis distances through
cached Cholesky factors, plus log determinants) and log priors.

The fit needs only sums of products over the labelled rows, which are added up on
the executors; the driver sees two small matrices. The statistics of a text are
computed once and written.

Defined results: null and empty texts have the statistics of no words and are
scored like others; documents without labels are scored, not learned from; of a
document labelled twice both labels count; with fewer than two rows of a class
the score is the share of label 1 (0.5 without labels); an empty table gives an
empty result; extra columns play no part.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, text_bytes

FEATURES = (
    "log_words", "log_mean_word", "capitals", "digits", "symbols", "shouts", "stops_commas", "other_marks", "line_breaks",
    "distinct_words", "stutter", "top_word", "dup_lines", "capital_starts", "high_bytes",
)
THRESHOLD = 0.3
POOLED = 0.1
RIDGE = 0.05
_CLASS = np.zeros(256, np.int64)
for _i, _chars in enumerate((b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b"#*$%&|<>", b"!", b".,", b"\"'()-/:;=?@[\\]^_`{}~+", b"\n", b" \t\x0b\x0c\r"), 1):
    _CLASS[list(_chars)] = _i
_CLASS[128:] = 9


def statistics(text: bytes) -> list[float]:
    """The transformed statistics of one text, in the order of FEATURES."""
    words = text.split()
    n, size = len(words), len(text)
    if not n:
        return [0.0] * len(FEATURES)
    kind = np.bincount(_CLASS, weights=np.bincount(np.frombuffer(text, np.uint8), minlength=256), minlength=10)
    share = np.sqrt(kind / size)
    counts = Counter(words)
    lines = [x for x in text.split(b"\n") if x.strip()]
    starts = sum(1 for w in words if 65 <= w[0] <= 90)
    return [
        float(np.log1p(n)), float(np.log((size - kind[8] - kind[7]) / n)), *share[1:8].tolist(),
        len(counts) / n**0.9, (sum(map(eq, words, words[1:])) / n) ** 0.5, (max(counts.values()) / n) ** 0.5,
        (1 - len(set(lines)) / len(lines)) ** 0.5, (starts / n) ** 0.5, float(share[9]),
    ]


def _statistics(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        x = np.array([statistics(t) for t in text_bytes(b.column("text"))]).reshape(-1, len(FEATURES))
        flat = pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), len(FEATURES)).cast(pa.list_(pa.float64()))
        yield pa.record_batch([b.column("doc_id"), flat], ["doc_id", "x"])


def features(docs: DataFrame) -> DataFrame:
    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(_statistics, f"doc_id {kind}, x array<double>")


@dataclass(frozen=True)
class Model:
    """Per class: mean, inverse Cholesky factor, log density offset."""

    mean: tuple[np.ndarray, ...]
    factor: tuple[np.ndarray, ...]
    offset: tuple[float, ...]
    share: float

    def score(self, x: np.ndarray) -> np.ndarray:
        if not self.mean:
            return np.full(len(x), self.share)
        density = [o - 0.5 * (((x - m) @ f.T) ** 2).sum(axis=1) for m, f, o in zip(self.mean, self.factor, self.offset, strict=True)]
        return 1 / (1 + np.exp(-np.clip(density[1] - density[0], -50, 50)))


def fit(labelled: DataFrame, pooled: float = POOLED, ridge: float = RIDGE) -> Model:
    """A model from rows of x (array<double>) and y (0 or 1), by one aggregation."""
    d = len(FEATURES)
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    sums = [F.count("*"), *[F.sum(F.col("x")[i]) for i in range(d)], *[F.sum(F.col("x")[i] * F.col("x")[j]) for i, j in pairs]]
    rows = {r[0]: r[1:] for r in labelled.filter("y in (0, 1)").groupBy("y").agg(*sums).collect()}
    n = [rows[y][0] if y in rows else 0 for y in (0, 1)]
    share = n[1] / sum(n) if sum(n) else 0.5
    if min(n) < 2:
        return Model((), (), (), share)
    mean, cov = [], []
    for y in (0, 1):
        m = np.array(rows[y][1 : d + 1], float) / n[y]
        s = np.zeros((d, d))
        for (i, j), v in zip(pairs, rows[y][d + 1 :], strict=True):
            s[i, j] = s[j, i] = v / n[y] - m[i] * m[j]
        mean.append(m)
        cov.append(s)
    together = (n[0] * cov[0] + n[1] * cov[1]) / sum(n)
    factor, offset = [], []
    for y in (0, 1):
        s = (1 - pooled) * cov[y] + pooled * together
        s = (1 - ridge) * s + ridge * np.diag(np.diag(s)) + 1e-4 * np.eye(d)
        low = np.linalg.cholesky(s)
        factor.append(np.linalg.inv(low))
        offset.append(float(np.log(n[y] / sum(n)) - np.log(np.diag(low)).sum()))
    return Model(tuple(mean), tuple(factor), tuple(offset), share)


def held_out(doc_id: Column) -> Column:
    """Whether a document's label may not be learned from: every fifth by checksum."""
    return F.crc32(F.encode(F.coalesce(doc_id.cast("string"), F.lit("")), "utf-8")) % 5 == 0


def _score(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.array(b.column("x").to_pylist(), float).reshape(-1, len(FEATURES))
            yield pa.record_batch([b.column("doc_id"), pa.array(model.score(x))], ["doc_id", "score"])

    return run


def classify(docs: DataFrame, labels: DataFrame, label: str = "quality") -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    x = materialise(features(docs), "stats")
    kind = docs.schema["doc_id"].dataType.simpleString()
    learn = labels.filter(~held_out(F.col("doc_id"))).select("doc_id", F.col(label).alias("y"))
    model = fit(x.join(learn, "doc_id"))
    out = x.mapInArrow(_score(model), f"doc_id {kind}, score double")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
