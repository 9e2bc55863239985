"""Accuracy measures. The triangle of a tall matrix has its singular values, so errors are taken on it in memory."""

from __future__ import annotations

import numpy as np

from tilerank.functions import kernels as K

from . import baselines, sketchqr, utv
from .matrix import Tall


def residual_norms(r: np.ndarray, approximation: np.ndarray) -> tuple[float, float]:
    d = r - approximation
    return float(np.linalg.norm(d, 2)), float(np.linalg.norm(d))


def rank_k_errors(mat: Tall, ks: list[int], b: int, seed: int) -> list[tuple]:
    """Error of each method's rank-k approximation over the best one, spectral and Frobenius."""
    r = mat.triangle()
    sv = np.linalg.svd(r, compute_uv=False)
    small = Tall(mat.df, mat.n)
    found = [("classical", 0, sketchqr.pivoted_qr(small)), ("sketched", 0, sketchqr.sketch_qr(small, b, None, "triangle", seed=seed))]
    found += [("utv", q, utv.power_utv(small, b, q, None, "triangle", seed)) for q in (0, 1, 2)]
    rows = []
    for name, q, f in found:
        for k in ks:
            if k >= len(sv):
                continue
            if name == "utv":
                lead = r @ f.v[:, :k]
                basis = np.linalg.qr(lead)[0]
            else:
                basis = np.linalg.qr(r[:, f.perm[:k]])[0]
            spectral, frob = residual_norms(r, basis @ (basis.T @ r))
            best = baselines.optimal_error(mat, k, sv)
            rows.append((name, k, q, spectral / best[0], frob / best[1]))
    return rows


def diag_deviation(mat: Tall, b: int, seed: int) -> list[tuple]:
    """Largest and mean relative deviation of the sorted diagonal of T from the singular values."""
    sv = np.linalg.svd(mat.triangle(), compute_uv=False)
    out = []
    for q in (0, 1, 2):
        d = np.sort(utv.power_utv(mat, b, q, None, "triangle", seed).diagonal())[::-1]
        dev = np.abs(d - sv[: len(d)]) / sv[: len(d)]
        out.append((q, float(dev.max()), float(dev.mean())))
    return out


def pivot_volumes(mat: Tall, k: int, b: int, seed: int) -> list[tuple]:
    """Logarithm of the volume of the chosen columns."""
    runs = [("classical", sketchqr.pivoted_qr(mat, k)), ("sketched", sketchqr.sketch_qr(mat, b, k, "triangle", seed=seed)), ("downdated", sketchqr.sketch_qr(mat, b, k, "left", "downdate", seed))]
    return [(name, float(np.log(np.abs(np.diag(f.r)[:k])).sum())) for name, f in runs]


def subspace_gaps(mat: Tall, k: int, seed: int) -> list[tuple]:
    """Sine of the largest angle between the right basis and the leading right singular vectors."""
    v = np.linalg.svd(mat.triangle())[2][:k].T
    out = []
    for q in (0, 1, 2):
        basis = utv.power_utv(mat, k, q, k, "triangle", seed).v[:, :k]
        out.append((q, float(np.linalg.norm(v - basis @ (basis.T @ v), 2))))
    return out


def lower_mass(t: np.ndarray) -> float:
    return float(np.abs(np.tril(t, -1)).sum())


def orthogonality(q: Tall) -> float:
    g = q.gram()
    return float(np.linalg.norm(g - np.eye(len(g))))


def invariants(mat: Tall, b: int, seed: int) -> list[tuple]:
    """Relative residual, departure from orthogonality and mass under the diagonal of each method."""
    scale = mat.frob()
    rows = []
    runs = [(f"sketchqr_{s}_{x or '-'}", sketchqr.sketch_qr(mat, b, None, s, x, seed)) for s, x in (("left", "project"), ("left", "upfront"), ("triangle", ""))]
    runs += [(f"utv_{s}_q{q}", utv.power_utv(mat, b, q, None, s, seed)) for s in ("left", "triangle") for q in (0, 1)]
    whole = mat.triangle()
    for name, f in runs:
        if isinstance(f, utv.UTV):
            u, t, back = f.u(), f.t[: f.k], f.t[: f.k] @ f.v.T
        else:
            u, t, back = f.q(), f.r, f.virtual()
        rows.append((name, abs(float(np.linalg.norm(K.positive(K.r_only(back)) - whole))) / scale, orthogonality(Tall(u, f.k)), lower_mass(t)))
    return rows
