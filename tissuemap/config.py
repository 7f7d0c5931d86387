"""Settings of a reconstruction. One frozen record, passed to every task."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class EngineConfig:
    """``match`` says when voxels are matched: every iteration, only at the ends,
    or never (the convex mode). ``step`` is fixed, backtrack or ratio."""

    algorithm: str = "sequential"
    match: str = "every"
    step: str = "fixed"
    calibrated: bool = False
    calibration: str = "one_step"
    rank: int = 10
    lam: float = 5e-4
    k_max: int = 10
    tv_iters: int = 5
    spatial: str = "tv"
    complex_mode: str = "joint"
    score: str = "modulus"
    residual_rule: str = "decrease"
    curvature: str = "normal"
    prox_scale: float = 1.0
    shrink: float = 0.5
    slack: float = 0.99
    max_try: int = 12
    #: Steps at or below this are taken unchecked. 0, as published, checks all.
    safe_step: float = 0.0

    def but(self, **changes) -> EngineConfig:
        return replace(self, **changes)


#: The six published configurations.
VARIANTS = {
    "seq_fixed": EngineConfig(),
    "seq_bt": EngineConfig(step="backtrack"),
    "seq_lazy": EngineConfig(match="ends", step="backtrack"),
    "seq_cal_lazy": EngineConfig(match="ends", step="backtrack", calibrated=True),
    "seq_cal_fixed": EngineConfig(calibrated=True),
    "par_bt": EngineConfig(algorithm="parallel", step="backtrack"),
}
#: Configurations beyond these: the other source of calibration, no matching, and
#: backtracking that takes steps of at most one unchecked (the operator is scaled to
#: a spectral radius of one).
STUDIES = {
    "seq_bt_safe": VARIANTS["seq_bt"].but(safe_step=1.0),
    "par_bt_safe": VARIANTS["par_bt"].but(safe_step=1.0),
    "seq_cal_lazy_raw": VARIANTS["seq_cal_lazy"].but(calibration="raw"),
    "convex": EngineConfig(match="none", step="backtrack"),
}
