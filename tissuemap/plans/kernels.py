"""Array kernels of one slice: encode, matching, regularisation, reconstruction.

They run inside a task on a few megabytes: a slice of N voxels in r components.
Images are (Q,) n, n, r arrays; k-space after the pass over raw samples is the
same shape, so nothing here grows with the sequence length.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from ..config import EngineConfig
from ..operators.matching import best_atoms

#: Above this rank the kernel per frequency cell is larger than it is worth.
KERNEL_RANK = 24


@dataclass
class Mask:
    """Sampled cells in order of cell: flat cell index, time, weight."""

    cell: np.ndarray
    t: np.ndarray
    w: np.ndarray

    @classmethod
    def of(cls, t, ku, kv, w, n: int) -> Mask:
        cell = np.asarray(ku) * n + np.asarray(kv)
        order = np.lexsort((t, cell))
        return cls(cell[order], np.asarray(t)[order], np.asarray(w, float)[order])


@dataclass
class Encoder:
    """The normal operator of one sequence in a basis, and its pieces."""

    n: int
    basis: np.ndarray
    mask: Mask
    coils: np.ndarray | None = None
    kernel: np.ndarray | None = field(default=None, repr=False)
    scale: float = 1.0

    def __post_init__(self) -> None:
        if self.kernel is None and self.basis.shape[1] <= KERNEL_RANK:
            self.kernel = self._build()

    def _build(self) -> np.ndarray:
        r = self.basis.shape[1]
        out = np.zeros((self.n * self.n, r, r), complex)
        b = self.basis[self.mask.t]
        edges = np.flatnonzero(np.r_[True, self.mask.cell[1:] != self.mask.cell[:-1]]) if len(self.mask.cell) else np.zeros(0, int)
        for i in range(r):
            for j in range(r):
                if len(edges):
                    out[self.mask.cell[edges], i, j] = np.add.reduceat(self.mask.w * b[:, i].conj() * b[:, j], edges)
        return out

    def in_basis(self, basis: np.ndarray) -> Encoder:
        return Encoder(self.n, basis, self.mask, self.coils, None, self.scale)

    def spread(self, u: np.ndarray) -> np.ndarray:
        x = u[None] if self.coils is None else self.coils[..., None] * u[None]
        return np.fft.fft2(x, axes=(1, 2), norm="ortho")

    def gather(self, s: np.ndarray) -> np.ndarray:
        x = np.fft.ifft2(s, axes=(1, 2), norm="ortho")
        return x[0] if self.coils is None else (self.coils.conj()[..., None] * x).sum(axis=0)

    def samples(self, u: np.ndarray) -> np.ndarray:
        """Q x M weighted samples in mask order."""
        s = self.spread(u).reshape(-1, self.n * self.n, u.shape[-1])
        return np.einsum("qmr,mr->qm", s[:, self.mask.cell], self.basis[self.mask.t].conj()) * np.sqrt(self.mask.w * self.scale)

    def adjoint(self, y: np.ndarray) -> np.ndarray:
        """Image of Q x M samples that carry their weights."""
        r = self.basis.shape[1]
        out = np.zeros((len(y), self.n * self.n, r), complex)
        edges = np.flatnonzero(np.r_[True, self.mask.cell[1:] != self.mask.cell[:-1]])
        b = self.basis[self.mask.t]
        for q, line in enumerate(y * np.sqrt(self.mask.w * self.scale)):
            out[q, self.mask.cell[edges]] = np.add.reduceat(line[:, None] * b, edges, axis=0)
        return self.gather(out.reshape(-1, self.n, self.n, r))

    def normal(self, u: np.ndarray) -> np.ndarray:
        if self.kernel is None:
            return self.adjoint(self.samples(u))
        s = self.spread(u)
        mixed = np.einsum("qcr,crk->qck", s.reshape(len(s), -1, s.shape[-1]), self.kernel) * self.scale
        return self.gather(mixed.reshape(s.shape))

    def spectral_radius(self, iters: int = 12) -> float:
        u = np.random.default_rng(0).normal(size=(self.n, self.n, self.basis.shape[1])).astype(complex)
        for _ in range(iters):
            u /= np.linalg.norm(u)
            v = self.normal(u)
            top = float(np.vdot(u, v).real)
            u = v
        return top


@dataclass
class Dictionary:
    """Atoms in the working basis, the norms that scores divide by, parameters."""

    atoms: np.ndarray
    norms: np.ndarray
    t1: np.ndarray
    t2: np.ndarray

    def rotated(self, w: np.ndarray) -> Dictionary:
        return Dictionary(self.atoms @ w, self.norms, self.t1, self.t2)


def project(u: np.ndarray, d: Dictionary, score: str = "modulus") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """New image, atom index and density of every voxel."""
    x = u.reshape(-1, u.shape[-1])
    at, _ = best_atoms(x, d.atoms, d.norms, score)
    a = d.atoms[at]
    rho = np.maximum(np.einsum("vr,vr->v", a, x.conj()).real / d.norms[at] ** 2, 0)
    return (rho[:, None] * a).reshape(u.shape), at.reshape(u.shape[:2]), rho.reshape(u.shape[:2])


def project_bins(u: np.ndarray, by_bin: dict[int, Dictionary], bins: np.ndarray, score: str = "modulus"):
    """As :func:`project`, each voxel with the dictionary of its field bin."""
    out, at, rho = np.zeros_like(u), np.zeros(u.shape[:2], np.int64), np.zeros(u.shape[:2])
    for b, d in by_bin.items():
        mine = bins == b
        if mine.any():
            new, k, p = project(u[mine][:, None], d, score)
            out[mine], at[mine], rho[mine] = new[:, 0], k[:, 0], p[:, 0]
    return out, at, rho


def gradient(u: np.ndarray) -> np.ndarray:
    g = np.zeros((2, *u.shape), u.dtype)
    g[0, :-1] = u[1:] - u[:-1]
    g[1, :, :-1] = u[:, 1:] - u[:, :-1]
    return g


def divergence(p: np.ndarray) -> np.ndarray:
    out = np.zeros_like(p[0])
    out[:-1] += p[0, :-1]
    out[1:] -= p[0, :-1]
    out[:, :-1] += p[1, :, :-1]
    out[:, 1:] -= p[1, :, :-1]
    return out


def estimate_coils(cells: np.ndarray, edge: int) -> np.ndarray:
    """Coil maps from the central ``edge`` x ``edge`` cells of the samples averaged
    over time: tapered, transformed, and divided by their root sum of squares.

    The first component of the basis is the average that weighs time points by
    their signal.
    """
    n = cells.shape[1]
    k = np.minimum(np.arange(n), n - np.arange(n))
    taper = np.where(k < edge / 2, np.cos(np.pi * k / (edge + 2)) ** 2, 0.0)
    low = np.fft.ifft2(cells[..., 0] * taper[:, None] * taper[None], axes=(1, 2), norm="ortho")
    total = np.sqrt((np.abs(low) ** 2).sum(axis=0))
    return low / np.maximum(total, 1e-9 * total.max())


def tv_norm(u: np.ndarray, joint: bool = False) -> float:
    g = (np.abs(gradient(u)) ** 2).sum(axis=0)
    return float(np.sqrt(g.sum(axis=-1) if joint else g).sum())


def tv_prox(z: np.ndarray, s: float, iters: int = 5, mode: str = "joint", joint: bool = False, tau: float = 0.125) -> np.ndarray:
    """Proximal map of s * TV by dual projection; s = 0 is the identity."""
    if s == 0:
        return z
    if mode == "split" and np.iscomplexobj(z):
        return tv_prox(z.real, s, iters, joint=joint, tau=tau) + 1j * tv_prox(z.imag, s, iters, joint=joint, tau=tau)
    p = np.zeros((2, *z.shape), z.dtype)
    for _ in range(iters):
        q = gradient(divergence(p) - z / s)
        size = (np.abs(q) ** 2).sum(axis=0)
        size = np.sqrt(size.sum(axis=-1, keepdims=True) if joint else size)
        p = (p + tau * q) / (1 + tau * size)
    return z - s * divergence(p)


def cycle_spin(z: np.ndarray, s: float, shifts: int = 2) -> np.ndarray:
    """Haar detail soft-thresholded, averaged over circular shifts."""
    out = np.zeros_like(z)
    soft = lambda d: d * np.maximum(1 - s / np.maximum(np.abs(d), 1e-300), 0)
    for i in range(shifts):
        for j in range(shifts):
            x = np.roll(z, (i, j), (0, 1))
            a, b, c, d = x[0::2, 0::2], x[0::2, 1::2], x[1::2, 0::2], x[1::2, 1::2]
            mean, h, v, g = (a + b + c + d) / 4, soft((a - b + c - d) / 2) / 2, soft((a + b - c - d) / 2) / 2, soft((a - b - c + d) / 2) / 2
            y = np.empty_like(x)
            y[0::2, 0::2], y[0::2, 1::2], y[1::2, 0::2], y[1::2, 1::2] = mean + h + v + g, mean - h + v - g, mean + h - v - g, mean - h - v + g
            out += np.roll(y, (-i, -j), (0, 1))
    return out / shifts**2


def low_pass(u: np.ndarray, radius: float) -> np.ndarray:
    n = len(u)
    k = np.minimum(np.arange(n), n - np.arange(n))
    keep = k[:, None] ** 2 + k[None, :] ** 2 <= radius**2
    return np.fft.ifft2(np.fft.fft2(u, axes=(0, 1)) * keep[..., None], axes=(0, 1))


def _regularise(z: np.ndarray, s: float, cfg: EngineConfig, k: int) -> np.ndarray:
    if cfg.spatial == "none":
        return z
    if cfg.spatial == "cycle_spin":
        return cycle_spin(z, s)
    if cfg.spatial == "low_pass":
        return low_pass(z, min(len(z), len(z) / 8 * (k + 1)))
    return tv_prox(z, s, cfg.tv_iters, cfg.complex_mode, cfg.spatial == "tv_joint")


@dataclass
class Result:
    image: np.ndarray
    atom: np.ndarray
    rho: np.ndarray
    history: list[dict]


def fidelity(u: np.ndarray, b: np.ndarray, yy: float, nu: np.ndarray) -> float:
    """|y - A u|^2 from the adjoint image, the power of y and the normal image."""
    return float(yy - 2 * np.vdot(b, u).real + np.vdot(u, nu).real)


def reconstruct(b: np.ndarray, yy: float, enc: Encoder, d: Dictionary, cfg: EngineConfig, match=None) -> Result:
    """Both splitting algorithms with all step rules; the iterate of the lowest
    fidelity is returned, with maps matched on it.

    sequential: gradient, match (every iteration, at the ends, or never), then
    the spatial prox. parallel: match and prox act side by side on reflected
    points, and their results are averaged. A rejected attempt halves the step
    and starts the iteration again from the same state. Where none of ``max_try``
    steps passes, a step of at most one is forced, and from then on such steps are
    taken unchecked; the history tells these outcomes apart.
    """
    match = match or (lambda z: project(z, d, cfg.score))
    u = np.zeros_like(b)
    zb, zs = np.zeros_like(b), np.zeros_like(b)
    nu = np.zeros_like(b)
    step, history, best, safe = 1.0, [], None, cfg.safe_step
    if cfg.step == "ratio":
        step = enc.n**2 / max(1.0, len(enc.mask.cell) / (enc.mask.t.max() + 1))
    for k in range(cfg.k_max):
        matched = cfg.match == "every" or cfg.match == "ends" and k in (0, cfg.k_max - 1)
        for attempt in range(cfg.max_try + 1):
            grad = nu - b
            if k == 0 and attempt == 0 and cfg.step != "ratio":
                # projections on a cone commute with the step, so it is chosen after
                x = match(b)[0] if matched else b
                nx = enc.normal(x)
                top = float(np.vdot(x, nx).real)
                step = float(np.vdot(b, x).real) / top if top > 0 else 1.0
                step = step if step > 0 else 1.0
            if attempt == 0:
                first = step
            elif attempt == cfg.max_try:
                step = min(first, 1.0)
                safe = max(safe, step)
            g = u - step * grad
            if cfg.algorithm == "parallel":
                ob, os_ = u - zb, u - zs
                zb2 = match(g + ob)[0] - ob
                zs2 = _regularise(g + os_, cfg.prox_scale * step * cfg.lam, cfg, k) - os_
                new = (zb2 + zs2) / 2
            else:
                z = match(g)[0] if matched else g
                new = _regularise(z, step * cfg.lam, cfg, k)
            nn = enc.normal(new)
            moved = float(np.linalg.norm(new - u) ** 2)
            if cfg.curvature == "normal":
                curved = float(np.linalg.norm(nn - nu) ** 2)
            else:
                curved = float(np.vdot(new - u, nn - nu).real)
            before, after = float(np.linalg.norm(b - nu) ** 2), float(np.linalg.norm(b - nn) ** 2)
            bound = cfg.slack * moved / curved if curved > 0 else np.inf
            ok_b = after <= before if cfg.residual_rule == "decrease" else after >= before
            passed = cfg.step == "fixed" or step <= bound and ok_b
            accepted = passed or step <= safe
            outcome = "forced" if attempt == cfg.max_try else "accepted" if passed else "unchecked" if accepted else "rejected"
            history.append({"iter": k, "attempt": attempt, "step": step, "fidelity": fidelity(new, b, yy, nn), "residual": after, "accepted": bool(accepted), "outcome": outcome})
            if accepted:
                break
            step *= cfg.shrink
        u, nu = new, nn
        if cfg.algorithm == "parallel":
            zb, zs = zb2, zs2
        if best is None or history[-1]["fidelity"] < best[0]:
            best = (history[-1]["fidelity"], u.copy())
    final = best[1] if best is not None else u
    new, at, rho = match(final)
    return Result(new, at, rho, history)


def calibration(b: np.ndarray, d: Dictionary, cfg: EngineConfig) -> np.ndarray:
    """Rotation R x r from one projected gradient step, or from the raw adjoint."""
    x = project(b, d, cfg.score)[0] if cfg.calibration == "one_step" else b
    x = x.reshape(-1, x.shape[-1])
    val, vec = np.linalg.eigh(x.conj().T @ x)
    return vec[:, ::-1][:, : cfg.rank]


def conjugate_gradient(b: np.ndarray, enc: Encoder, iters: int = 30, tol: float = 1e-6) -> tuple[np.ndarray, list[dict]]:
    u, r = np.zeros_like(b), b.copy()
    p, rr, history = r.copy(), float(np.vdot(r, r).real), []
    first = rr
    for k in range(iters):
        if rr <= tol**2 * first or rr == 0:
            break
        q = enc.normal(p)
        a = rr / float(np.vdot(p, q).real)
        u, r = u + a * p, r - a * q
        new = float(np.vdot(r, r).real)
        history.append({"iter": k, "attempt": 0, "step": a, "fidelity": float("nan"), "residual": new, "accepted": True, "outcome": "accepted"})
        p, rr = r + (new / rr) * p, new
    return u, history


def time_mix(b_cells: np.ndarray, enc: Encoder, eps: float = 1e-2) -> np.ndarray:
    """Per cell the least-squares component spectrum that explains its samples."""
    r = enc.basis.shape[1]
    k = (enc.kernel if enc.kernel is not None else enc._build()) * enc.scale
    load = eps * np.trace(k, axis1=1, axis2=2).real / r + 1e-12
    a = np.swapaxes(k + load[:, None, None] * np.eye(r), 1, 2)
    q, n = len(b_cells), enc.n
    c = np.linalg.solve(a[None], b_cells.reshape(q, n * n, r)[..., None])[..., 0]
    return enc.gather(c.reshape(q, n, n, r))


def nuclear_prox(u: np.ndarray, tau: float) -> np.ndarray:
    x = u.reshape(-1, u.shape[-1])
    val, vec = np.linalg.eigh(x.conj().T @ x)
    s = np.sqrt(np.maximum(val, 0))
    return ((x @ vec) * (np.maximum(s - tau, 0) / np.maximum(s, 1e-300)) @ vec.conj().T).reshape(u.shape)


def nuclear(b: np.ndarray, enc: Encoder, tau: float, iters: int = 15) -> np.ndarray:
    a = 1 / max(enc.spectral_radius(), 1e-12)
    u = np.zeros_like(b)
    for _ in range(iters):
        u = nuclear_prox(u - a * (enc.normal(u) - b), a * tau)
    return u


def local_lowrank(u: np.ndarray, block: int = 8, r: int = 4) -> np.ndarray:
    """Each block of voxels replaced by its nearest matrix of rank r."""
    out = np.empty_like(u)
    for i in range(0, len(u), block):
        for j in range(0, len(u), block):
            x = u[i : i + block, j : j + block]
            a, s, v = np.linalg.svd(x.reshape(-1, x.shape[-1]), full_matrices=False)
            out[i : i + block, j : j + block] = ((a[:, :r] * s[:r]) @ v[:r]).reshape(x.shape)
    return out


def patch_lowrank(u: np.ndarray, patch: int = 3, similar: int = 12, r: int = 4, reach: int = 5, stride: int = 2) -> np.ndarray:
    """Similar patches nearby stacked and truncated along each mode, averaged."""
    n, rank = len(u), u.shape[-1]
    spots = [(i, j) for i in range(0, n - patch + 1) for j in range(0, n - patch + 1)]
    flat = {s: u[s[0] : s[0] + patch, s[1] : s[1] + patch].reshape(-1, rank) for s in spots}
    total, count = np.zeros_like(u), np.zeros((n, n))
    for i, j in spots:
        if i % stride or j % stride:
            continue
        near = [(a, c) for a in range(max(0, i - reach), min(n - patch, i + reach) + 1) for c in range(max(0, j - reach), min(n - patch, j + reach) + 1)]
        near = sorted(near, key=lambda s: (float(np.abs(flat[s] - flat[i, j]).sum()), s))[:similar]
        t = np.stack([flat[s] for s in near])
        for mode, keep in enumerate((r, r, r)):
            m = np.moveaxis(t, mode, 0)
            a, s, v = np.linalg.svd(m.reshape(m.shape[0], -1), full_matrices=False)
            t = np.moveaxis(((a[:, :keep] * s[:keep]) @ v[:keep]).reshape(m.shape), 0, mode)
        for s, p in zip(near, t, strict=True):
            total[s[0] : s[0] + patch, s[1] : s[1] + patch] += p.reshape(patch, patch, rank)
            count[s[0] : s[0] + patch, s[1] : s[1] + patch] += 1
    return np.where(count[..., None] > 0, total / np.maximum(count, 1)[..., None], u)
