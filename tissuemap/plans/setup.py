"""What all slices of one scan share: schedule, mask, dictionary, bases.

Its size depends on the sequence and the parameter grid, never on the number of
slices, so it is made once on the driver and broadcast.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np

from ..operators.dictionary import T1_RANGES, T2_RANGES, coherent_signals, epg_signals, values
from ..operators.sequence import INTERLEAVES, LATE_TURN, LOBE, TR_PERIOD, TURN
from ..operators.subspace import leading
from .kernels import Dictionary, Encoder, Mask


def schedule_arrays(length: int) -> tuple[np.ndarray, np.ndarray]:
    """TR and flip angle; the array twin of ``sequence.pulse_schedule``."""
    t = np.arange(length)
    height = 0.3 + 0.7 * np.abs(np.sin(1.7 * (t // LOBE) + 0.6))
    return 13.55 + 1.45 * np.sin(2 * np.pi * t / TR_PERIOD), 74.0 * height * np.sin(np.pi * (t % LOBE) / LOBE)


def spiral_points(length: int, n: int, samples: int, inner: float, outer: float) -> tuple[np.ndarray, ...]:
    """t, kx, ky of the points on the rotating spirals, in cells."""
    edge = n / 2 - 0.5
    grow = (outer - inner) / edge / (2 * math.pi)
    last = math.log(1 + grow * edge * 2 * math.pi / inner) / grow
    winding = np.sqrt((np.arange(samples) + 0.5) / samples) * last
    radius = inner / (2 * math.pi * grow) * (np.exp(grow * winding) - 1)
    t = np.arange(length)
    late = t // INTERLEAVES
    angle = np.radians(((t - late) * TURN + late * LATE_TURN) % 360.0)
    turn = winding[None] + angle[:, None]
    return np.repeat(t, samples), (radius * np.cos(turn)).ravel(), (radius * np.sin(turn)).ravel()


def spiral_cells(length: int, n: int, samples: int, inner: float, outer: float) -> tuple[np.ndarray, ...]:
    """t, ku, kv, w of the sampled cells; the array twin of ``sampling_mask``."""
    t, kx, ky = spiral_points(length, n, samples, inner, outer)
    cell = lambda v: np.mod(np.trunc(v + np.copysign(0.5, v)).astype(np.int64), n)
    code = np.unique(t * n * n + cell(kx) * n + cell(ky))
    t, cells = code // (n * n), code % (n * n)
    met = np.bincount(cells, minlength=n * n)[cells]
    return t, cells // n, cells % n, length / met


def gain_weights(t, ku, kv, n: int, basis: np.ndarray) -> np.ndarray:
    """Weights under which every sampled cell has a gain of one: the inverse of
    the largest eigenvalue of what its time points add up to in the basis.

    Counting repetitions alone leaves cells whose few time points resemble each
    other with several times the gain of others. The largest of them then fixes
    the step, and the rest converge slowly.
    """
    plain = Encoder(n, basis, Mask.of(t, ku, kv, np.ones(len(t)), n))
    top = np.linalg.eigvalsh(plain.kernel)[:, -1]
    return 1 / np.maximum(top[np.asarray(ku) * n + np.asarray(kv)], 1e-12)


@lru_cache(8)
def grid_arrays(every: int = 1) -> tuple[np.ndarray, np.ndarray]:
    pairs = [(a, b) for a in values(T1_RANGES) for b in values(T2_RANGES) if a >= b][::every]
    return np.array([p[0] for p in pairs], float), np.array([p[1] for p in pairs], float)


@dataclass
class Setup:
    """One sequence length: encoder at full rank and dictionary in that basis."""

    n: int
    length: int
    basis: np.ndarray
    dictionary: Dictionary
    mask: tuple[np.ndarray, ...] = field(repr=False)
    scale: float
    coils: np.ndarray | None = None
    by_bin: dict[int, Dictionary] | None = None
    bins: np.ndarray | None = None
    energy: np.ndarray | None = None
    #: Edge of the centre of k-space from which each slice's coil maps are made; 0
    #: takes ``coils`` as they are.
    centre: int = 0

    @property
    def grid(self) -> int:
        """Edge of the cells that a slice's state has."""
        return self.n

    def encoder(self, r: int) -> Encoder:
        return Encoder(self.n, self.basis[:, :r], Mask.of(*self.mask, self.n), self.coils, None, self.scale)

    def atoms(self, r: int) -> Dictionary:
        return _cut(self.dictionary, r)

    def bin_atoms(self, r: int) -> dict[int, Dictionary] | None:
        return self.by_bin and {b: _cut(d, r) for b, d in self.by_bin.items()}


def _cut(d: Dictionary, r: int) -> Dictionary:
    a = d.atoms[:, :r]
    return Dictionary(a, np.linalg.norm(a, axis=1), d.t1, d.t2)


def simulate(t1, t2, length: int, model: str = "coherent", b1: float = 1.0) -> np.ndarray:
    tr, fa = schedule_arrays(length)
    t1, t2 = np.asarray(t1, float), np.asarray(t2, float)
    return epg_signals(t1, t2, tr, fa, b1=b1) if model == "epg" else coherent_signals(t1, t2, tr, fa * b1)


def make(
    n: int, length: int, rank: int = 30, inner: float = 3.0, outer: float = 6.0, model: str = "coherent", every: int = 1,
    coils: np.ndarray | None = None, bins: np.ndarray | None = None, factors: dict[int, float] | None = None, weights: str = "gain", centre: int = 0,
) -> Setup:
    """``rank`` is the largest rank that any method will ask for; ``weights`` is
    "gain", or "count", which only evens out how often a cell is met."""
    t1, t2 = grid_arrays(every)
    signals = simulate(t1, t2, length, model)
    val, basis = leading(signals.conj().T @ signals, min(rank, length))
    own = lambda s: Dictionary(s @ basis, np.linalg.norm(s @ basis, axis=1), t1, t2)
    by_bin = factors and {b: own(simulate(t1, t2, length, model, f)) for b, f in factors.items()}
    mask = spiral_cells(length, n, samples=int(6 * n * n / (inner + outer)) + 8, inner=inner, outer=outer)
    if weights == "gain":
        mask = (*mask[:3], gain_weights(*mask[:3], n, basis[:, : min(10, basis.shape[1])]))
    small = Encoder(n, basis[:, : min(10, basis.shape[1])], Mask.of(*mask, n), coils)
    return Setup(n, length, basis, own(signals), mask, 1 / max(small.spectral_radius(40), 1e-12), coils, by_bin, bins, val, centre)
