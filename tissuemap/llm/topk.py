"""Exact top-k search by inner product with a pivot-distance index.

Vectors are keyed by their nearest pivot and their distance to it, and each
pivot's vectors are cut by distance into rings (annuli). For a query q at distance
D from the pivot, a vector v at distance d is at least |D - d| away, and
<q, v> = (|q|^2 + |v|^2 - |q - v|^2) / 2, which bounds every ring's best score
from above. A query visits rings in order of this bound: first as many as hold k
vectors, then further ones in widening steps, each only if its bound still
reaches the k-th score found so far. It stops where no bound does. The bounds are
exact, so the result is, whatever the pivots; these are fitted on a bounded sample
and only decide the speed.

Rings are a table of fixed size, their vectors are not: the index is a written
table dealt by ring and id, so one ring, or one vector repeated, fills many tasks.
Queries come in blocks of ``BLOCK`` rows, which are broadcast; a task multiplies
its vectors by the queries that still want their ring and keeps the k-th scores
running. No table of queries by rings or by vectors is ever made.

Scores: components are whole numbers. While sums of products stay below 2^53 they
are formed in doubles, up to 2^63 in 64-bit integers, beyond in integers of any
length; a score beyond a long counts as the nearest long.

Defined results: null vectors and those with null or non-finite components take
no part as query or candidate; shorter vectors count as padded with zeros; ties
go to the smaller vec_id; a repeated id counts as a row of its own, as query and
as candidate, and a query is never matched with rows of its own id; a null id
takes no part; an empty table gives an empty result.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise, run_starts, scratch_dir

PIVOTS = 32
#: Rings of a pivot.
RINGS = 32
#: Vectors from which pivots and the borders of rings are fitted; all are indexed.
SAMPLE = 4096
#: Queries that are broadcast together.
BLOCK = 4096
K = 10
#: Products that a task forms at once.
PAIRS = 1 << 18
#: Rings that a query may visit in a step, by the number of the step; the last
#: figure holds for all later ones.
STEPS = (8, 64, 1 << 30)
LONG = (1 << 63) - 1
MATCH = "row int, vec_id long, score long"


def integer_vectors(df: DataFrame, scale: int = 1024) -> DataFrame:
    """vec_id and components floor(scale * x) as doubles, which hold them exactly."""
    whole = F.transform("embedding", lambda x: _floor(x.cast("double") * scale))
    bad = F.exists("embedding", lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double") * scale) == float("inf")))
    return df.filter(F.col("embedding").isNotNull()).filter(~bad).select("vec_id", whole.alias("v"))


def _floor(x):
    """The floor of a double as a double; from 2^52 on every double is whole."""
    return F.when(F.abs(x) < float(1 << 52), F.floor(x).cast("double")).otherwise(x)


def _matrix(rows: list, width: int) -> np.ndarray:
    out = np.zeros((len(rows), width))
    for i, r in enumerate(rows):
        out[i, : len(r)] = r
    return out


def _vectors(column: pa.Array, width: int) -> np.ndarray:
    """A list column as a matrix, padded with zeros."""
    flat, lengths = column.flatten().to_numpy(zero_copy_only=False), column.value_lengths().to_numpy()
    if len(lengths) and (lengths == width).all():
        return flat.reshape(-1, width)
    out = np.zeros((len(lengths), width))
    inside = np.arange(width) < lengths[:, None]
    out[inside] = flat
    return out


def _distances(x: np.ndarray, p: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum((x**2).sum(1)[:, None] + (p**2).sum(1) - 2 * x @ p.T, 0))


@dataclass
class Layout:
    """Pivots, and per pivot the distances that part its rings."""

    points: np.ndarray
    borders: np.ndarray

    @property
    def width(self) -> int:
        return self.points.shape[1]

    def place(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ring of each vector and its distance to the ring's pivot."""
        d = _distances(x, self.points)
        near = d.argmin(axis=1)
        dist = d[np.arange(len(d)), near]
        return near * RINGS + (dist[:, None] >= self.borders[near]).sum(axis=1), dist


def layout(vectors: DataFrame, width: int, count: int = PIVOTS, sample: int = SAMPLE) -> Layout | None:
    """Farthest-first pivots from a sample of at most ``sample`` vectors, taken by
    the hash of the id, and the quantiles of its distances."""
    rows = vectors.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).collect()
    if not rows:
        return None
    x = _matrix([r["v"] for r in rows], width)
    chosen = [0]
    far = ((x - x[0]) ** 2).sum(axis=1)
    while len(chosen) < min(count, len(x)) and far.max() > 0:
        chosen.append(int(far.argmax()))
        far = np.minimum(far, ((x - x[chosen[-1]]) ** 2).sum(axis=1))
    d = _distances(x, x[chosen])
    near, least = d.argmin(axis=1), d.min(axis=1)
    parts = np.arange(1, RINGS) / RINGS
    return Layout(x[chosen], np.array([np.quantile(least[near == p], parts) if (near == p).any() else np.zeros(RINGS - 1) for p in range(len(chosen))]))


def _keyed(plan: Layout):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _vectors(b.column("v"), plan.width)
            ring, dist = plan.place(x) if len(x) else (np.zeros(0, np.int64), np.zeros(0))
            own = [pa.array(ring.astype(np.int32)), pa.array(dist), pa.array((x**2).sum(axis=1)), pa.array(np.abs(x).max(axis=1, initial=0.0))]
            yield pa.record_batch([b.column("vec_id"), b.column("v"), *own], ["vec_id", "v", "ring", "dist", "norm2", "top"])

    return run


@dataclass
class Index:
    """The written vectors, and arrays over their rings (at most PIVOTS * RINGS)."""

    vectors: DataFrame
    plan: Layout
    ring: np.ndarray
    near: np.ndarray
    far: np.ndarray
    norm2: np.ndarray
    size: np.ndarray
    top: float

    def bounds(self, norm2: np.ndarray, dist: np.ndarray, rings=slice(None)) -> np.ndarray:
        """Upper bounds on scores, queries by rings. The slack covers rounding in
        the distances."""
        to = dist[:, self.ring[rings] // RINGS]
        least = np.maximum(0, np.maximum(to - self.far[rings], self.near[rings] - to))
        both = norm2[:, None] + self.norm2[rings]
        return (both - least**2) / 2 + 1e-6 * both + 1


def index(vectors: DataFrame, count: int = PIVOTS, tasks: int | None = None) -> Index | None:
    """Every vector with its ring, dealt by ring and id."""
    width = vectors.agg(F.max(F.size("v"))).first()[0]
    plan = layout(vectors, width, count) if width else None
    if plan is None:
        return None
    keyed = materialise(vectors.mapInArrow(_keyed(plan), "vec_id long, v array<double>, ring int, dist double, norm2 double, top double"), "keyed")
    rings = keyed.groupBy("ring").agg(
        F.min("dist").alias("near"), F.max("dist").alias("far"), F.max("norm2").alias("norm2"), F.count("*").alias("n"), F.max("top").alias("top")
    )
    rows = sorted(rings.collect())
    tasks = tasks or int(vectors.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = keyed.repartitionByRange(tasks, "ring", "vec_id").sortWithinPartitions("ring").select("ring", "vec_id", "v")
    column = lambda name: np.array([r[name] for r in rows])
    return Index(materialise(dealt, "rings"), plan, column("ring"), column("near"), column("far"), column("norm2"), column("n"), max(r["top"] for r in rows))


@dataclass
class _Block:
    """A block of queries: what tasks need of them."""

    ids: np.ndarray
    v: np.ndarray
    norm2: np.ndarray
    dist: np.ndarray
    edge: np.ndarray


def _kind(top: float, width: int) -> type:
    """The numbers in which products of whole vectors add up exactly."""
    most = int(top) ** 2 * width
    return float if most < 1 << 53 else np.int64 if most < 1 << 63 else object


def _whole(x: np.ndarray, kind: type) -> np.ndarray:
    if kind is object:
        return np.array([[int(y) for y in row] for row in x], object).reshape(x.shape)
    return x.astype(kind)


def best_rows(row: np.ndarray, ids: np.ndarray, score: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best of each row: score falling, then id rising."""
    order = np.lexsort((ids, -score, row))
    start = run_starts(row[order])
    at = np.arange(len(order)) - np.repeat(start, np.diff(np.append(start, len(order))))
    return order[at < k]


def _scan(shared, k: int):
    """The best matches of a block of queries among the vectors of one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, idx, wanted, kind = shared.value
        of = {int(r): i for i, r in enumerate(idx.ring)}
        edge = block.edge.copy()
        v = _whole(block.v, kind)
        row, ids, score = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        for b in batches:
            if not b.num_rows:
                continue
            ring, vec_id = b.column("ring").to_numpy(), b.column("vec_id").to_numpy()
            x = _whole(_vectors(b.column("v"), block.v.shape[1]), kind)
            starts = run_starts(ring)
            for lo, hi in zip(starts, np.append(starts[1:], len(ring)), strict=True):
                i = of[int(ring[lo])]
                near = np.flatnonzero(np.unpackbits(wanted[:, i], count=len(edge)))
                near = near[idx.bounds(block.norm2[near], block.dist[near], [i])[:, 0] >= edge[near]]
                few = max(1, PAIRS // int(hi - lo))
                for part in range(0, len(near), few):
                    mine = near[part : part + few]
                    s = v[mine] @ x[lo:hi].T
                    s = s.astype(np.int64) if kind is not object else np.minimum(np.maximum(s, -LONG), LONG).astype(np.int64)
                    at, which = np.nonzero((s >= edge[mine][:, None]) & (block.ids[mine][:, None] != vec_id[lo:hi]))
                    if not len(at):
                        continue
                    held = np.isin(row, mine)
                    r = np.concatenate([row[held], mine[at]])
                    i2 = np.concatenate([ids[held], vec_id[lo:hi][which]])
                    s2 = np.concatenate([score[held], s[at, which]])
                    best = best_rows(r, i2, s2, k)
                    r, i2, s2 = r[best], i2[best], s2[best]
                    raise_edges(edge, r, s2, k)
                    row, ids, score = (np.concatenate([a[~held], z]) for a, z in ((row, r), (ids, i2), (score, s2)))
        yield pa.record_batch([pa.array(row.astype(np.int32)), pa.array(ids), pa.array(score)], ["row", "vec_id", "score"])

    return run


def raise_edges(edge: np.ndarray, row: np.ndarray, score: np.ndarray, k: int) -> None:
    """Set the edge of each row that has k matches to a double no larger than its
    k-th score; rows are grouped, their best first."""
    start = run_starts(row)
    full = start[np.diff(np.append(start, len(row))) >= k]
    for r, y in zip(row[full].tolist(), score[full + k - 1].tolist(), strict=True):
        x = float(y)
        edge[r] = max(edge[r], x if int(x) <= y else np.nextafter(x, -np.inf))


def _answer(idx: Index, queries: pa.Table, k: int, top: float, visits: list) -> pa.Table:
    """Matches of one block of queries."""
    spark = idx.vectors.sparkSession
    v = _vectors(queries.column("v").combine_chunks(), max(idx.plan.width, max(map(len, queries.column("v").to_pylist()), default=0)))
    n, width = len(v), idx.plan.width
    norm2 = (v**2).sum(axis=1)
    # what a query has beyond the width of the vectors adds to all distances alike
    dist = np.sqrt(_distances(v[:, :width], idx.plan.points) ** 2 + (v[:, width:] ** 2).sum(axis=1)[:, None])
    block = _Block(queries.column("vec_id").to_numpy(), v[:, :width], norm2, dist, np.full(n, -np.inf))
    bound = idx.bounds(norm2, dist)
    order = np.argsort(-bound, axis=1, kind="stable")
    place = np.empty_like(order)
    np.put_along_axis(place, order, np.arange(order.shape[1])[None], axis=1)
    # one more than k: a query may meet itself
    held = np.cumsum(idx.size[order], axis=1)
    reach = 1 + (held <= k).sum(axis=1)
    done = np.zeros(n, np.int64)
    row, ids, score = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    kind = _kind(max(top, idx.top), width)
    step = 0
    while True:
        want = (place >= done[:, None]) & (place < reach[:, None]) & (bound >= block.edge[:, None])
        if want.any():
            rings = np.flatnonzero(want.any(axis=0))
            visits.append(int((want * idx.size).sum()))
            light = Index(None, idx.plan, idx.ring, idx.near, idx.far, idx.norm2, idx.size, idx.top)
            shared = spark.sparkContext.broadcast((block, light, np.packbits(want, axis=0), kind))
            some = idx.vectors.filter(F.col("ring").isin([int(x) for x in idx.ring[rings]]))
            found = some.mapInArrow(_scan(shared, k), MATCH)
            got = _best_of(found, k).toArrow()
            row = np.concatenate([row, got.column("row").to_numpy()])
            ids, score = np.concatenate([ids, got.column("vec_id").to_numpy()]), np.concatenate([score, got.column("score").to_numpy()])
            keep = best_rows(row, ids, score, k)
            row, ids, score = row[keep], ids[keep], score[keep]
            shared.unpersist()
            raise_edges(block.edge, row, score, k)
        done = reach
        if (done >= order.shape[1]).all() or not ((place >= done[:, None]) & (bound >= block.edge[:, None])).any():
            break
        reach = np.minimum(done + STEPS[min(step, len(STEPS) - 1)], order.shape[1])
        step += 1
    start = run_starts(row)
    rank = np.arange(len(row)) - np.repeat(start, np.diff(np.append(start, len(row)))) + 1
    return pa.table({"query_id": block.ids[row], "rank": rank.astype(np.int32), "vec_id": ids, "score": score})


def _best_of(found: DataFrame, k: int) -> DataFrame:
    """The k best of each query over all tasks; each sends at most k of its own."""
    order = Window.partitionBy("row").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("_rank", F.row_number().over(order)).filter(F.col("_rank") <= k).drop("_rank")


def search(vectors: DataFrame, queries: DataFrame, k: int = K, block: int = BLOCK, count: int = PIVOTS, report: dict | None = None) -> DataFrame:
    """query_id, rank, vec_id, score: the k best of ``vectors`` for each query.

    Both have vec_id and v (whole numbers as doubles). ``report`` receives the
    number of vectors visited and of all pairs of a query and a vector.
    """
    spark = vectors.sparkSession
    shape = "query_id long, rank int, vec_id long, score long"
    vectors, queries = (x.filter(F.col("vec_id").isNotNull()).select(F.col("vec_id").cast("long").alias("vec_id"), "v") for x in (vectors, queries))
    idx = index(vectors, count)
    if idx is None:
        return spark.createDataFrame([], shape)
    n, top = queries.agg(F.count("*"), F.max(F.array_max(F.transform("v", F.abs)))).first()
    path = f"{scratch_dir(spark)}/queries-{uuid.uuid4().hex}"
    # files of at most ``block`` rows
    queries.repartition(max(1, -(-n // block))).write.option("maxRecordsPerFile", block).parquet(path)
    visits: list[int] = []
    out = f"{scratch_dir(spark)}/matches-{uuid.uuid4().hex}"
    spark.createDataFrame([], shape).write.parquet(out)
    for file in sorted(spark.read.schema(queries.schema).parquet(path).inputFiles()) if n else []:
        found = _answer(idx, spark.read.schema(queries.schema).parquet(file).toArrow(), k, top or 0.0, visits)
        spark.createDataFrame(found).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score").write.mode("append").parquet(out)
    if report is not None:
        report |= {"visited": sum(visits), "pairs": int(idx.size.sum()) * n}
    return spark.read.schema(shape).parquet(out)
