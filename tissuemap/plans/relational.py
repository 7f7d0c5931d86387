"""Both algorithms as DataFrame plans, one row per coefficient.

For tests against SQL and for images beyond a task's memory. The state is cut by
a written table after each accepted iteration; the driver sees scalars only.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import EngineConfig
from ..operators import encode, spatial
from ..operators.matching import exhaustive_join
from ..sources.scratch import cut

KEYS = ["slice_id", "row", "col", "comp"]


@dataclass
class Problem:
    """Adjoint image b, kernel and interleaved atoms (id, x, norm) of a scan."""

    n: int
    b: DataFrame
    kernel: DataFrame
    atoms: DataFrame
    coils: DataFrame | None = None

    def normal(self, u: DataFrame) -> DataFrame:
        return encode.normal(u, self.n, self.kernel, self.coils)


def combine(a: DataFrame, x: float, b: DataFrame, y: float) -> DataFrame:
    """x * a + y * b over equal keys."""
    o = b.select(*KEYS, F.col("re").alias("_r"), F.col("im").alias("_i"))
    return a.join(o, KEYS).select(*KEYS, (x * F.col("re") + y * F.col("_r")).alias("re"), (x * F.col("im") + y * F.col("_i")).alias("im"))


def zero(b: DataFrame) -> DataFrame:
    return b.select(*KEYS, F.lit(0.0).alias("re"), F.lit(0.0).alias("im"))


def match_image(u: DataFrame, atoms: DataFrame) -> tuple[DataFrame, DataFrame]:
    """New image and (slice_id, row, col, atom_id, rho)."""
    cell = F.struct("slice_id", "row", "col")
    packed = u.groupBy(cell.alias("id")).agg(F.sort_array(F.collect_list(F.struct("comp", "re", "im"))).alias("p"))
    packed = packed.select("id", F.flatten(F.transform("p", lambda v: F.array(v["re"], v["im"]))).alias("x"))
    best = exhaustive_join(packed, atoms, keep=True)
    re = F.aggregate(F.zip_with("x", "a", lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    dense = best.withColumn("rho", F.greatest(re / (F.col("norm") * F.col("norm")), F.lit(0.0)))
    maps = dense.select("id.slice_id", "id.row", "id.col", "atom_id", "rho")
    comp = F.posexplode(F.transform(F.sequence(F.lit(0), F.size("a") - 2, F.lit(2)), lambda i: F.struct(F.get("a", i).alias("r"), F.get("a", i + 1).alias("i"))))
    new = dense.select("id", "rho", comp.alias("comp", "v"))
    return new.select("id.slice_id", "id.row", "id.col", "comp", (F.col("rho") * F.col("v.r")).alias("re"), (F.col("rho") * F.col("v.i")).alias("im")), maps


def gradient_point(u: DataFrame, p: Problem, step: float) -> DataFrame:
    return combine(combine(u, 1.0, p.normal(u), -step), 1.0, p.b, step)


def sequential_step(u: DataFrame, p: Problem, step: float, cfg: EngineConfig, matched: bool, first: bool = False) -> DataFrame:
    """Gradient, match unless skipped, spatial prox."""
    z = p.b.select(*KEYS, (step * F.col("re")).alias("re"), (step * F.col("im")).alias("im")) if first else gradient_point(u, p, step)
    if matched:
        z = match_image(z, p.atoms)[0]
    return spatial.tv_prox(z, step * cfg.lam, cfg.tv_iters, cfg.complex_mode)


def parallel_step(state: tuple[DataFrame, DataFrame, DataFrame], p: Problem, step: float, cfg: EngineConfig) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(u, zb, zs) to the next; both branches start from the same gradient point.

    The point and both offsets stand side by side in one written row per
    coefficient, so that neither branch plans the gradient again.
    """
    named = lambda df, k: df.select(*KEYS, F.col("re").alias(f"{k}re"), F.col("im").alias(f"{k}im"))
    wide = named(state[0], "u")
    for df, k in ((p.normal(state[0]), "n"), (p.b, "y"), (state[1], "b"), (state[2], "s")):
        wide = wide.join(named(df, k), KEYS)
    parts = []
    for c in ("re", "im"):
        g = F.col(f"u{c}") - step * F.col(f"n{c}") + step * F.col(f"y{c}")
        for k in ("b", "s"):
            off = F.col(f"u{c}") - F.col(f"{k}{c}")
            parts += [off.alias(f"o{k}{c}"), (g + off).alias(f"x{k}{c}")]
    wide = cut(wide.select(*KEYS, *parts))
    part = lambda k: wide.select(*KEYS, F.col(f"{k}re").alias("re"), F.col(f"{k}im").alias("im"))
    zb2 = combine(match_image(part("xb"), p.atoms)[0], 1.0, part("ob"), -1.0)
    zs2 = combine(spatial.tv_prox(part("xs"), cfg.prox_scale * step * cfg.lam, cfg.tv_iters, cfg.complex_mode), 1.0, part("os"), -1.0)
    return combine(zb2, 0.5, zs2, 0.5), zb2, zs2


def _scalars(u: DataFrame, new: DataFrame, nu: DataFrame, nn: DataFrame, b: DataFrame):
    named = lambda df, k: df.select(*KEYS, F.col("re").alias(f"{k}r"), F.col("im").alias(f"{k}i"))
    x = named(u, "u").join(named(new, "n"), KEYS).join(named(nu, "p"), KEYS).join(named(nn, "q"), KEYS).join(named(b, "b"), KEYS)
    sq = lambda a, c: F.sum((F.col(f"{a}r") - F.col(f"{c}r")) ** 2 + (F.col(f"{a}i") - F.col(f"{c}i")) ** 2)
    dot = lambda a, c: F.sum(F.col(f"{a}r") * F.col(f"{c}r") + F.col(f"{a}i") * F.col(f"{c}i"))
    return x.agg(sq("u", "n").alias("moved"), sq("p", "q").alias("curved"), sq("b", "p").alias("before"), sq("b", "q").alias("after"), dot("b", "n").alias("bn"), dot("n", "q").alias("nq")).first()


def solve(p: Problem, power: float, cfg: EngineConfig):
    """Image, maps and history of the iterate with the lowest fidelity.

    One aggregate decides an attempt; a rejected one halves the step and leaves
    the state as it was.
    """
    u = cut(zero(p.b))
    zb = zs = nu = u
    matched = cfg.match in ("every", "ends")
    x = match_image(p.b, p.atoms)[0] if matched else p.b
    x = cut(x)
    s = _scalars(u, x, u, cut(p.normal(x)), p.b)
    step = s["bn"] / s["nq"] if s["nq"] > 0 and s["bn"] > 0 else 1.0
    history, best, safe = [], None, cfg.safe_step
    for k in range(cfg.k_max):
        every = cfg.match == "every" or cfg.match == "ends" and k in (0, cfg.k_max - 1)
        first = step
        for attempt in range(cfg.max_try + 1):
            if attempt == cfg.max_try:
                step = min(first, 1.0)
                safe = max(safe, step)
            if cfg.algorithm == "parallel":
                state = tuple(cut(d) for d in parallel_step((u, zb, zs), p, step, cfg))
                new = state[0]
            else:
                new = cut(sequential_step(u, p, step, cfg, every, k == 0))
            nn = cut(p.normal(new))
            s = _scalars(u, new, nu, nn, p.b)
            passed = cfg.step == "fixed" or (step <= cfg.slack * s["moved"] / max(s["curved"], 1e-300) and (s["after"] <= s["before"]) == (cfg.residual_rule == "decrease"))
            ok = passed or step <= safe
            outcome = "forced" if attempt == cfg.max_try else "accepted" if passed else "unchecked" if ok else "rejected"
            history.append((k, attempt, step, power - 2 * s["bn"] + s["nq"], s["after"], ok, outcome))
            if ok:
                break
            step *= cfg.shrink
        u, nu = new, nn
        if cfg.algorithm == "parallel":
            zb, zs = state[1], state[2]
        if best is None or history[-1][3] < best[0]:
            best = (history[-1][3], u)
    image, maps = match_image(best[1] if best else u, p.atoms)
    spark = p.b.sparkSession
    return image, maps, spark.createDataFrame(history, "iter int, attempt int, step double, fidelity double, residual double, accepted boolean, outcome string")
