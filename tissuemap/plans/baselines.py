"""The methods compared with, rebuilt from published general techniques."""

from __future__ import annotations

import numpy as np

from ..config import EngineConfig
from .kernels import Dictionary, Encoder, conjugate_gradient, local_lowrank, nuclear, patch_lowrank, reconstruct, time_mix, tv_prox

#: The four that were measured, and those that were only described.
MEASURED = ("base_zero_fill", "base_proj_grad", "base_time_mix", "base_subspace")
DESCRIBED = ("base_proj_grad_ratio", "base_proj_lp", "base_nuclear", "base_patch", "base_local")


def run(name: str, cells: np.ndarray, b: np.ndarray, power: float, enc: Encoder, d: Dictionary, cfg: EngineConfig, match):
    """Atom and density maps, and the history where the method iterates."""
    history: list[dict] = []
    if name == "base_zero_fill":
        u = b
    elif name in ("base_proj_grad", "base_proj_grad_ratio", "base_proj_lp"):
        # projection after each gradient step; no spatial prior, or a low-pass
        # that widens with the iterations
        own = cfg.but(algorithm="sequential", match="every", calibrated=False, spatial="low_pass" if name == "base_proj_lp" else "none", step="ratio" if name == "base_proj_grad_ratio" else "backtrack")
        out = reconstruct(b, power, enc, d, own, match)
        return out.atom, out.rho, out.history
    elif name == "base_time_mix":
        if cells.shape[1] != enc.n:
            raise ValueError("base_time_mix solves cell by cell and needs samples on the grid")
        u = time_mix(cells, enc)
    elif name in ("base_subspace", "base_subspace_10"):
        u, history = conjugate_gradient(b, enc)
    elif name == "base_nuclear":
        u = nuclear(b, enc, 0.02 * float(np.linalg.norm(b.reshape(-1, b.shape[-1]), 2)))
    elif name == "base_patch":
        u = patch_lowrank(conjugate_gradient(b, enc, 8)[0])
    elif name == "base_local":
        u = tv_prox(local_lowrank(conjugate_gradient(b, enc, 8)[0]), cfg.lam)
    else:
        raise ValueError(f"unknown method {name}")
    if name == "base_zero_fill":
        x = match(u)[0]
        nx = enc.normal(x)
        top = float(np.vdot(x, nx).real)
        u = u * (float(np.vdot(b, x).real) / top if top > 0 else 1.0)
    _, atom, rho = match(u)
    return atom, rho, history
