"""Fingerprint matching: exhaustive, calibrated, by field bin, and accelerated.

Voxels and atoms are packed rows (id, x). Real signals are arrays of doubles;
complex ones interleave real and imaginary parts (re0, im0, re1, im1, ...), so
that one matrix product serves both.
"""

from __future__ import annotations

import os
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.cx import v_dot

#: Voxels that a thread takes at once; their product with this many atoms bounds what
#: a task holds where scores are compared as rounded.
VOXELS, ATOMS = 2048, 1024
#: Voxels and atoms of one product of complex rows: its result stays in a core's cache.
ROWS, WIDE = 16, 8192
#: Bytes of atoms that a task holds at once.
ATOM_BYTES = 64 << 20
#: Scores are compared at this precision, so that engines agree on ties.
DIGITS = 9


def _pair_score(x: Column, a: Column, norm: Column, score: str) -> Column:
    if score == "real":
        return v_dot(x, a) / norm
    if score == "absolute":
        return F.abs(v_dot(x, a)) / norm
    # <atom, voxel> with interleaved parts: sum of a * conj(x)
    half = F.sequence(F.lit(0), F.size(x) - 2, F.lit(2))
    re = v_dot(x, a)
    im = F.aggregate(half, F.lit(0.0), lambda s, i: s + F.get(a, i + 1) * F.get(x, i) - F.get(a, i) * F.get(x, i + 1))
    return F.hypot(re, im) / norm


def exhaustive_join(voxels: DataFrame, atoms: DataFrame, score: str = "modulus", keep: bool = False) -> DataFrame:
    """id, atom_id, score by a nested-loop join; ties go to the smallest atom. With
    ``keep`` the rows come along: x, a and norm.

    ``atoms`` is a dictionary, whose size is fixed by its parameter grid and is
    checked by the planner before this form is chosen. All pairs of a voxel are
    made in one partition, so partial maxima leave one row per voxel to shuffle.
    """
    a = F.broadcast(atoms.select(F.col("id").alias("atom_id"), F.col("x").alias("a"), F.col("norm")))
    pairs = voxels.select("id", "x").crossJoin(a)
    s = F.round(_pair_score(F.col("x"), F.col("a"), F.col("norm"), score), DIGITS)
    rows = ("x", "a", "norm") if keep else ()
    best = pairs.select("id", F.struct(s.alias("s"), (-F.col("atom_id")).alias("k"), *rows).alias("b")).groupBy("id").agg(F.max("b").alias("b"))
    return best.select("id", (-F.col("b.k")).alias("atom_id"), F.col("b.s").alias("score"), *[f"b.{c}" for c in rows])


def best_atoms(x: np.ndarray, atoms: np.ndarray, norms: np.ndarray, score: str = "modulus") -> tuple[np.ndarray, np.ndarray]:
    """Row of the winning atom and its score, for complex or real rows of x.

    ``TISSUEMAP_THREADS`` blocks of voxels are searched at once, for tasks that have
    several cores to themselves.
    """
    unit = atoms / norms[:, None]
    complex_, turned = np.iscomplexobj(unit), score != "real" and np.iscomplexobj(x)
    # parts side by side, so that one real product gives all sums
    table = np.concatenate([unit.real, unit.imag], axis=1).T if complex_ else np.ascontiguousarray(unit.real.T)
    best, where = np.full(len(x), -np.inf), np.zeros(len(x), np.int64)

    def rows(part: np.ndarray) -> np.ndarray:
        if not complex_:
            return np.concatenate([part.real, part.imag]) if turned else np.ascontiguousarray(part.real)
        own = np.concatenate([part.real, part.imag], axis=1)
        return np.concatenate([own, np.concatenate([-part.imag, part.real], axis=1)]) if score != "real" else own

    def search(first: int) -> None:
        for lo in range(first, min(first + VOXELS, len(x)), ROWS):
            left, n = rows(x[lo : lo + ROWS]), min(ROWS, len(x) - lo)
            top, at = np.full(n, -np.inf), np.zeros(n, np.int64)
            for k in range(0, len(unit), WIDE):
                c = left @ table[:, k : k + WIDE]
                if score != "real":  # squares order like moduli
                    np.multiply(c, c, out=c)
                    if len(c) > n:
                        c[:n] += c[n:]
                        c = c[:n]
                i = c.argmax(axis=1)
                v = c[np.arange(n), i]
                better = v > top
                top[better], at[better] = v[better], i[better] + k
            best[lo : lo + n], where[lo : lo + n] = top if score == "real" else np.sqrt(top), at

    threads = int(os.environ.get("TISSUEMAP_THREADS", "1"))
    if threads > 1 and len(x) > VOXELS:
        with ThreadPoolExecutor(threads) as pool:
            list(pool.map(search, range(0, len(x), VOXELS)))
    else:
        for lo in range(0, len(x), VOXELS):
            search(lo)
    return where, best


def _stack(rows, interleaved: bool) -> np.ndarray:
    x = np.array(list(rows), float)
    return x[:, 0::2] + 1j * x[:, 1::2] if interleaved else x


def _blocks(atoms: DataFrame, limit: int) -> list[DataFrame]:
    """The atoms in parts of about ``limit`` bytes; the driver and each task hold
    one part at a time."""
    n, width = atoms.agg(F.count("*"), F.coalesce(F.max(F.size("x")), F.lit(0))).first()
    parts = max(1, -(-n * (width + 2) * 8 // limit))
    if parts == 1:
        return [atoms]
    return [atoms.filter(F.pmod(F.xxhash64("id"), F.lit(parts)) == k) for k in range(parts)]


def _products(voxels: DataFrame, atoms: DataFrame, score: str, interleaved: bool, new: bool) -> DataFrame:
    table = atoms.select("id", "x", "norm").orderBy("id").toPandas()
    ids, norms = table["id"].to_numpy(), table["norm"].to_numpy()
    raw = np.array(table["x"].tolist(), float)
    d = _stack(table["x"], interleaved)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if b.empty or not len(ids):
                continue
            at, s = best_atoms(_stack(b["x"], interleaved), d, norms, score) if interleaved or score == "modulus" else _best_in_order(_stack(b["x"], False), d, norms, score)
            # products by blocks and by pairs differ in the last digits
            out = pd.DataFrame({"id": b["id"], "atom_id": ids[at], "score": np.round(s, DIGITS)})
            if new:
                rho = np.maximum(np.einsum("vt,vt->v", raw[at], np.array(b["x"].tolist(), float)) / norms[at] ** 2, 0)
                out = out.assign(rho=rho, x=list(rho[:, None] * raw[at]))
            yield out

    return voxels.select("id", "x").mapInPandas(run, "id long, atom_id long, score double" + (", rho double, x array<double>" if new else ""))


def exhaustive_blocks(voxels: DataFrame, atoms: DataFrame, score: str = "modulus", interleaved: bool = False, new: bool = False, limit: int = ATOM_BYTES) -> DataFrame:
    """As :func:`exhaustive_join` by blocked matrix products, and with ``new`` the
    density and new row as well, which the task has at hand.

    Nothing is shuffled while the atoms fit ``limit`` bytes; more of them come in
    parts, and the winners of the parts are reduced to one row per voxel.
    """
    parts = [_products(voxels, a, score, interleaved, new) for a in _blocks(atoms, limit)]
    if len(parts) == 1:
        return parts[0]
    rest = ("rho", "x") if new else ()
    best = F.max(F.struct("score", (-F.col("atom_id")).alias("k"), *rest)).alias("b")
    out = reduce(DataFrame.unionByName, parts).groupBy("id").agg(best)
    return out.select("id", (-F.col("b.k")).alias("atom_id"), "b.score", *[f"b.{c}" for c in rest])


def with_norm(atoms: DataFrame) -> DataFrame:
    return atoms.withColumn("norm", F.sqrt(v_dot(F.col("x"), F.col("x"))))


def density(matched: DataFrame, voxels: DataFrame, atoms: DataFrame) -> DataFrame:
    """``matched`` with rho: the clipped real projection on the winning atom."""
    a = atoms.select(F.col("id").alias("atom_id"), F.col("x").alias("a"), "norm")
    out = matched.join(voxels.select("id", "x"), "id").join(a, "atom_id")
    return out.withColumn("rho", F.greatest(v_dot(F.col("x"), F.col("a")) / (F.col("norm") * F.col("norm")), F.lit(0.0)))


def resynth(dense: DataFrame) -> DataFrame:
    """id and the new row: density times atom."""
    return dense.select("id", F.transform("a", lambda v: v * F.col("rho")).alias("x"))


def lookup(matched: DataFrame, params: DataFrame) -> DataFrame:
    """Tissue parameters of the winning atoms."""
    return matched.join(params.withColumnRenamed("id", "atom_id"), "atom_id")


def project(voxels: DataFrame, atoms: DataFrame, score: str = "modulus", interleaved: bool = False) -> DataFrame:
    """id, atom_id, score, rho, x (new row): matching as a projection."""
    return exhaustive_blocks(voxels, atoms, score, interleaved, new=True)


def rotate(atoms: DataFrame, rotation: DataFrame) -> DataFrame:
    """Atoms times a rotation (comp, comp2, w), keeping the old norm: what
    calibrated matching correlates with, made once instead of per voxel."""
    w = rotation.groupBy("comp2").agg(F.sort_array(F.collect_list(F.struct("comp", "w"))).alias("c"))
    table = w.groupBy().agg(F.transform(F.sort_array(F.collect_list(F.struct("comp2", "c"))), lambda r: F.transform(r["c"], lambda e: e["w"])).alias("rot"))
    out = atoms.crossJoin(F.broadcast(table))
    return out.withColumn("x", F.transform("rot", lambda col: v_dot(F.col("x"), col))).drop("rot")


def _pair_dot(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products of rows, added up in order as ``v_dot`` does, so that equal rows give
    equal sums wherever they stand."""
    out = np.zeros(len(a))
    for k in range(a.shape[1]):
        out += a[:, k] * b[:, k]
    return out


def _decide(v: np.ndarray, k: np.ndarray, x: np.ndarray, d: np.ndarray, norms: np.ndarray, score: str) -> tuple[np.ndarray, np.ndarray]:
    """Of candidate pairs (row ``v`` of x, row ``k`` of d) the one of the best rounded
    score for each of the voxels, ties to the first atom; every voxel needs a pair."""
    best, at = np.full(len(x), -np.inf), np.full(len(x), len(d), np.int64)
    scores = np.empty(len(v))
    for lo in range(0, len(v), 1 << 16):
        part = slice(lo, lo + (1 << 16))
        c = _pair_dot(d[k[part]], x[v[part]]) / norms[k[part]]
        scores[part] = np.round(c if score == "real" else np.abs(c), DIGITS)
    np.maximum.at(best, v, scores)
    won = scores == best[v]
    np.minimum.at(at, v[won], k[won])
    return at, best


def _best_in_order(x: np.ndarray, d: np.ndarray, norms: np.ndarray, score: str) -> tuple[np.ndarray, np.ndarray]:
    """As :func:`best_atoms` for real rows, with scores compared as rounded: products
    find what can win, and pairs within the rounding of the best are scored anew."""
    unit = (d / norms[:, None]).T
    at, best = np.zeros(len(x), np.int64), np.zeros(len(x))
    step = max(1, VOXELS * ATOMS // len(d))
    for lo in range(0, len(x), step):
        part = x[lo : lo + step]
        c = part @ unit
        if score != "real":
            np.abs(c, out=c)
        v, k = np.nonzero(c >= c.max(axis=1, keepdims=True) - 2 * 10.0**-DIGITS)
        at[lo : lo + step], best[lo : lo + step] = _decide(v, k, part, d, norms, score)
    return at, best


def by_bin(voxels: DataFrame, atoms: DataFrame, bin_col: str, score: str = "absolute", limit: int = ATOM_BYTES) -> DataFrame:
    """Matching within equal values of ``bin_col``, by a matrix product for each bin
    of a batch; null bins match nothing.

    No pair of a voxel and an atom becomes a row. Atoms come in parts of ``limit``
    bytes; voxels are dealt by id, as a file may come in fewer parts than cores.
    """
    parts = [_bin_products(voxels, a, bin_col, score) for a in _blocks(atoms, limit)]
    best = reduce(DataFrame.unionByName, parts).groupBy("id", bin_col).agg(F.max(F.struct("score", (-F.col("atom_id")).alias("k"))).alias("b"))
    return best.select("id", bin_col, (-F.col("b.k")).alias("atom_id"), "b.score")


def _bin_products(voxels: DataFrame, atoms: DataFrame, bin_col: str, score: str) -> DataFrame:
    table = atoms.filter(F.col(bin_col).isNotNull()).select("id", bin_col, "x", "norm").orderBy("id").toPandas()
    bins = {k: (t["id"].to_numpy(), np.array(t["x"].tolist(), float), t["norm"].to_numpy()) for k, t in table.groupby(bin_col)}

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for key, mine in b.groupby(bin_col):
                if key in bins:
                    ids, d, norms = bins[key]
                    at, s = _best_in_order(np.array(mine["x"].tolist(), float), d, norms, score)
                    yield pd.DataFrame({"id": mine["id"], bin_col: mine[bin_col], "atom_id": ids[at], "score": s})

    kind = voxels.schema[bin_col].dataType.simpleString()
    return voxels.filter(F.col(bin_col).isNotNull()).select("id", bin_col, "x").repartition("id").mapInPandas(run, f"id long, {bin_col} {kind}, atom_id long, score double")


def _aligned(x: np.ndarray) -> np.ndarray:
    """Unit rows with the sign (phase) of their largest entry taken out."""
    x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
    top = x[np.arange(len(x)), np.abs(x).argmax(axis=1)]
    return x * (np.conj(top) / np.maximum(np.abs(top), 1e-300))[:, None]


def _approximate(voxels: DataFrame, search) -> DataFrame:
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                yield pd.DataFrame({"id": b["id"], "atom_id": search(np.array(b["x"].tolist()))})

    return voxels.select("id", "x").mapInPandas(run, "id long, atom_id long")


def _atom_arrays(atoms: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    t = atoms.select("id", "x").orderBy("id").toPandas()
    return t["id"].to_numpy(), np.array(t["x"].tolist())


def lsh(voxels: DataFrame, atoms: DataFrame, tables: int = 8, bits: int = 5, seed: int = 1) -> DataFrame:
    """id, atom_id by random hyperplanes: candidates share a bucket in some table
    and are scored exactly; a voxel without candidates is matched exhaustively."""
    ids, raw = _atom_arrays(atoms)
    unit = _aligned(raw)
    planes = np.random.default_rng(seed).normal(size=(tables, bits, unit.shape[1]))
    code = lambda x: ((np.einsum("nd,tbd->ntb", x, planes) > 0) << np.arange(bits)).sum(-1)
    buckets = [{} for _ in range(tables)]
    for k, line in enumerate(code(unit)):
        for t, c in enumerate(line):
            buckets[t].setdefault(int(c), []).append(k)

    def search(x: np.ndarray) -> np.ndarray:
        x, out = _aligned(x), []
        for v, line in zip(x, code(x), strict=True):
            near = sorted({k for t, c in enumerate(line) for k in buckets[t].get(int(c), ())}) or range(len(unit))
            near = np.array(list(near))
            out.append(ids[near[np.abs(unit[near] @ v).argmax()]])
        return np.array(out)

    return _approximate(voxels, search)


def tree(voxels: DataFrame, atoms: DataFrame, leaf: int = 256) -> DataFrame:
    """id, atom_id by an exact ball tree over unit atoms and their negatives; scores
    are compared as rounded, ties go to the first atom.

    Voxels descend together: each first to the leaf that is nearest by centres, then
    all through the tree, where a ball keeps those that it may hold a better point
    for. A leaf is one matrix product.
    """
    table = atoms.select("id", "x", "norm").orderBy("id").toPandas()
    ids, norms = table["id"].to_numpy(), table["norm"].to_numpy()
    raw = np.array(table["x"].tolist(), float)
    unit = raw / norms[:, None]
    points, owner = np.concatenate([unit, -unit]), np.concatenate([np.arange(len(unit))] * 2)

    def grow(rows: np.ndarray):
        mine = points[rows]
        centre = mine.mean(axis=0)
        radius = float(np.sqrt(((mine - centre) ** 2).sum(axis=1).max()))
        if len(rows) <= leaf:
            return centre, radius, rows, None
        axis = mine.var(axis=0).argmax()
        order = rows[np.argsort(mine[:, axis], kind="stable")]
        return centre, radius, None, (grow(order[: len(order) // 2]), grow(order[len(order) // 2 :]))

    if not len(ids):
        return voxels.select("id", F.lit(None).cast("long").alias("atom_id")).limit(0)
    root = grow(np.arange(len(points)))

    def search(x: np.ndarray) -> np.ndarray:
        size = np.maximum(np.linalg.norm(x, axis=1), 1e-300)
        v = x / size[:, None]
        top = np.full(len(v), -np.inf)
        slack = 2 * 10.0**-DIGITS / size + 1e-12  # of a rounded score, in cosines
        pairs: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

        def scan(node, active: np.ndarray, keep: bool) -> None:
            c = v[active] @ points[node[2]].T
            top[active] = np.maximum(top[active], c.max(axis=1))
            if keep:
                i, k = np.nonzero(c >= (top - slack)[active, None])
                pairs.append((active[i], owner[node[2][k]], c[i, k]))

        def descend(node, active: np.ndarray) -> None:
            if not len(active):
                return
            if node[3] is None:
                scan(node, active, False)
                return
            left, right = node[3]
            nearer = v[active] @ (left[0] - right[0]) * 2 >= left[0] @ left[0] - right[0] @ right[0]
            descend(left, active[nearer])
            descend(right, active[~nearer])

        def visit(node, active: np.ndarray) -> None:
            far = np.sqrt(np.maximum(1 - 2 * (v[active] @ node[0]) + node[0] @ node[0], 0))
            # points at a distance of d have a cosine of 1 - d * d / 2
            active = active[1 - np.maximum(far - node[1] - 1e-9, 0) ** 2 / 2 >= (top - slack)[active]]
            if not len(active):
                return
            if node[3] is None:
                scan(node, active, True)
                return
            for child in node[3]:
                visit(child, active)

        every = np.arange(len(v))
        descend(root, every)
        visit(root, every)
        i, k, c = (np.concatenate(p) for p in zip(*pairs, strict=True))
        last = c >= (top - slack)[i]
        return ids[_decide(i[last], k[last], x, raw, norms, "absolute")[0]]

    return _approximate(voxels.repartition("id"), search)


def group(voxels: DataFrame, atoms: DataFrame, groups: int | None = None, keep: int = 3, seed: int = 1) -> DataFrame:
    """id, atom_id by group search: correlate with group centres, then search the
    best ``keep`` groups. Keeping all groups is the exhaustive search."""
    ids, raw = _atom_arrays(atoms)
    unit = _aligned(raw)
    groups = min(groups or int(np.sqrt(len(unit))) or 1, len(unit))
    rng = np.random.default_rng(seed)
    centre = unit[rng.choice(len(unit), groups, replace=False)]
    for _ in range(12):
        label = np.abs(unit @ centre.T).argmax(axis=1)
        for g in range(groups):
            if (label == g).any():
                mine = unit[label == g]
                mine = mine * np.sign(mine @ centre[g])[:, None]
                centre[g] = mine.mean(axis=0) / max(np.linalg.norm(mine.mean(axis=0)), 1e-300)
    members = [np.flatnonzero(label == g) for g in range(groups)]

    def search(x: np.ndarray) -> np.ndarray:
        x = _aligned(x)
        top = np.argsort(-np.abs(x @ centre.T), axis=1, kind="stable")[:, :keep]
        out = []
        for v, chosen in zip(x, top, strict=True):
            near = np.sort(np.concatenate([members[g] for g in chosen]))
            out.append(ids[near[np.abs(unit[near] @ v).argmax()]] if len(near) else ids[0])
        return np.array(out)

    return _approximate(voxels, search)


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """One row: share of voxels with the exhaustive search's atom."""
    e = exact.select("id", F.col("atom_id").alias("want"))
    return found.join(e, "id").agg(F.count("*").alias("voxels"), F.avg((F.col("atom_id") == F.col("want")).cast("double")).alias("recall"))
