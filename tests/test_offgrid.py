"""Samples off the grid: fast transforms against sums, and reconstructions."""

from __future__ import annotations

import numpy as np
import pytest
from tissuemap.plans import offgrid
from tissuemap.plans.setup import spiral_cells, spiral_points


def adjoint(s, y, r):
    """Sum over all samples, pixel by pixel."""
    t, kx, ky, w = s.mask
    x = np.arange(s.n) - s.n // 2
    ex, ey = np.exp(2j * np.pi / s.n * kx[:, None] * x), np.exp(2j * np.pi / s.n * ky[:, None] * x)
    return np.einsum("m,mr,mx,my->xyr", w * y, s.basis[t, :r], ex, ey, optimize=True) / s.n


@pytest.fixture(scope="module")
def scan():
    return offgrid.make_offgrid(12, 40, 5, 1.5, 3.0, every=20)


def test_window_pair():
    u, x = np.linspace(-3, 3, 20001), np.array([0.0, 3.0, 7.0])
    for v in x:
        direct = (offgrid.window(u) * np.cos(2 * np.pi * u * v / 48)).sum() * (u[1] - u[0])
        assert direct == pytest.approx(offgrid.window_transform(np.array([v]), 48)[0], rel=1e-3)


def test_adjoint_equals_the_sum(scan):
    rng = np.random.default_rng(0)
    y = rng.normal(size=len(scan.mask[0])) + 1j * rng.normal(size=len(scan.mask[0]))
    t, kx, ky, w = scan.mask
    cells = offgrid.spread((w * y)[:, None] * scan.basis[t], 2 * kx, 2 * ky, scan.grid)
    got, want = scan.encoder(5).gather(cells[None]), adjoint(scan, y, 5)
    assert np.abs(got - want).max() < 1e-4 * np.abs(want).max()


def test_normal_operator_equals_forward_then_adjoint(scan):
    rng = np.random.default_rng(1)
    u = rng.normal(size=(12, 12, 5)) + 1j * rng.normal(size=(12, 12, 5))
    t, kx, ky, _ = scan.mask
    spectra = offgrid.ndft(np.moveaxis(u, -1, 0), kx, ky)
    y = (spectra * scan.basis[t].conj()).sum(axis=1)
    got, want = scan.encoder(5).normal(u), adjoint(scan, y, 5) * scan.scale
    assert np.abs(got - want).max() < 1e-4 * np.abs(want).max()
    rotation = np.linalg.qr(rng.normal(size=(5, 3)))[0]
    enc = scan.encoder(5)
    turned = enc.in_basis(enc.basis @ rotation)
    assert np.allclose(turned.normal(u[..., :3]), enc.normal(u[..., :3] @ rotation.T) @ rotation, atol=1e-8)
    assert 0.99 < enc.spectral_radius(60) < 1.02


def test_points_round_to_the_cells():
    t, kx, ky = spiral_points(30, 16, 200, 1.5, 3.0)
    got = {(a, int(round(b)) % 16, int(round(c)) % 16) for a, b, c in zip(t, kx, ky) if abs(b % 1 - 0.5) > 1e-9 and abs(c % 1 - 0.5) > 1e-9}
    a, b, c, _ = spiral_cells(30, 16, 200, 1.5, 3.0)
    assert got <= set(zip(a.tolist(), b.tolist(), c.tolist()))


def test_state_and_maps_of_a_scan(spark):
    from tissuemap.config import EngineConfig
    from tissuemap.plans.setup import simulate
    from tissuemap.plans.slices import run_slices

    s = offgrid.make_offgrid(12, 60, 8, 1.5, 3.0, every=10)
    kind = np.add.outer(np.arange(12) // 6, np.arange(12) // 6) % 2
    t1, t2 = np.array([800.0, 1500.0]), np.array([80.0, 160.0])
    sig = simulate(t1, t2, 60)
    samples = offgrid.phantom_points(spark, np.stack([(kind == k) * 1.0 for k in (0, 1)]), sig, s)
    rows = sorted((r["t"], r["s"], r["re"] + 1j * r["im"]) for r in samples.collect())
    state = offgrid.reduce_points(samples, s).cache()
    t, kx, ky, w = s.mask
    y = np.array([v for *_, v in rows])
    want = offgrid.spread((w * y)[:, None] * s.basis[t], 2 * kx, 2 * ky, s.grid)
    for r in state.collect():
        got = np.array(r["cells"])
        assert np.allclose(got[0::2] + 1j * got[1::2], want[r["ku"], r["kv"]], atol=1e-8)
    assert sum(r["power"] for r in state.collect()) == pytest.approx(float((w * np.abs(y) ** 2).sum()))
    maps = run_slices(state, [s], ["par_bt", "base_zero_fill"], EngineConfig(lam=1e-3)).collect()
    err = {m: np.mean([abs(r["t1"] - t1[kind[r["row"], r["col"]]]) / t1[kind[r["row"], r["col"]]] for r in maps if r["method"] == m]) for m in ("par_bt", "base_zero_fill")}
    assert err["par_bt"] < 0.15 and err["par_bt"] < err["base_zero_fill"]
