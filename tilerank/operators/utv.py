"""Blocked randomized UTV, A = U T V': sketch and power steps turn the columns, small SVDs make the diagonal.

For tall matrices the left factor stays implicit: with the leading triangle of T, its first s columns are
A V1 T11^-1, which is row-local. Schedules:

* ``right``: the matrix in the turned basis, less what is finished, is written anew at each step;
* ``left``: A is only read; each product with T22' T22 is a pass with A'A corrected by finished rows, and each step ends
  one column panel of T;
* ``triangle``: one pass makes the triangle of [A | G], the rest runs on the driver (parallel BLAS).
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from tilerank.functions import kernels as K
from tilerank.functions.keyed import DRAWS

from .matrix import Tall, write_step
from .sketchqr import low


@dataclass
class UTV:
    """``t`` (k x n, upper triangular), ``v`` (n x n); U row by row on demand."""

    mat: Tall
    t: np.ndarray
    v: np.ndarray
    k: int
    passes: int
    written: int = 0

    def diagonal(self) -> np.ndarray:
        return np.diag(self.t)[: self.k]

    def u(self) -> DataFrame:
        """The first k columns of U as a row frame."""
        v1, t11 = self.v[:, : self.k], self.t[: self.k, : self.k]
        return self.mat.map_rows(lambda _, a: K.right_solve(a @ v1, t11))

    def reconstruct(self, k: int | None = None) -> DataFrame:
        """U1 T1 V', the rank-k approximation, as a row frame."""
        k = self.k if k is None else k
        v1, t11, tv = self.v[:, :k], self.t[:k, :k], self.t[:k] @ self.v.T
        return self.mat.map_rows(lambda _, a: K.right_solve(a @ v1, t11) @ tv)

    def rank(self, tol: float = 1e-8) -> int:
        d = np.abs(self.diagonal())
        return int((d > tol * d.max()).sum()) if d.size and d.max() > 0 else 0


def power_utv(mat: Tall, b: int, q: int = 1, k: int | None = None, schedule: str = "left", seed: int = 7, rng: str = "md5", tol: float = 1e-10) -> UTV:
    if q < 0 or b < 1:
        raise ValueError("power steps are not negative, blocks not empty")
    n = mat.n
    k = n if k is None else min(k, n)
    b = min(b, n)
    draw = DRAWS[rng]
    if schedule == "triangle":
        width = -(-k // b) * b
        whole = mat.triangle(None, lambda ids: draw(seed, ids, width))
        _, t, v = K.utv(whole[:, :n], b, q, whole[:, n:], k)
        done = min(n, -(-k // b) * b)
        return UTV(mat, np.triu(t[:n]), v, min(k, done), mat.passes)
    if schedule not in ("left", "right"):
        raise ValueError(f"no schedule {schedule}")
    return (left if schedule == "left" else right)(mat, b, q, k, seed, draw, tol)


def turned(y: np.ndarray, v: np.ndarray, s: int) -> np.ndarray:
    """V with its trailing columns turned toward the sketch."""
    _, w, c = K.reflectors(y)
    out = v.copy()
    out[:, s:] = K.apply_right(w, c, v[:, s:])
    return out


def left(mat: Tall, b: int, q: int, k: int, seed: int, draw, tol: float) -> UTV:
    n = mat.n
    v, t = np.eye(n), np.zeros((n, n))
    done = 0
    for s in range(0, k, b):
        w = min(b, n - s)
        e = s + w
        v1, t11 = v[:, :s].copy(), t[:s, :s].copy()

        def products(ids, a, s=s, w=w, v1=v1, t11=t11):
            g, u = draw(seed, ids, w, s), K.right_solve(a @ v1, t11)
            return np.vstack([np.hstack([g.T @ a, np.zeros((w, w))]), np.hstack([u.T @ a, u.T @ g])])

        if e < n:
            both = mat.reduce(products)  # A'G, U1'A and U1'G in one pass
            ag, rows, ug = both[:w, :n].T, both[w:, :n], both[w:, n:]
            y = v[:, s:].T @ (ag - rows.T @ ug)
            for _ in range(q):
                x = v[:, s:] @ np.linalg.qr(y)[0]
                y = v[:, s:].T @ (mat.gram_times(x) - rows.T @ (rows @ x))
            v = turned(y, v, s)
        lead = v[:, :e].copy()
        r = K.positive(low(mat.reduce(lambda _, a, lead=lead: K.r_only(a @ lead), K.r_only), e))  # fewer rows than columns: zero rows
        x, d, z = K.small_svd(r[s:e, s:e])
        v[:, s:e] = v[:, s:e] @ z
        t[:s, s:e] = r[:s, s:e] @ z
        t[range(s, e), range(s, e)] = d
        done = e
        if d[-1] <= tol * t[0, 0]:
            done = s + int((d > tol * t[0, 0]).sum())
            break
    k = min(k, done)
    if done < n or k < n:
        v1, t11 = v[:, :k], t[:k, :k]
        t[:k] = mat.reduce(lambda _, a: K.right_solve(a @ v1, t11).T @ a) @ v
        t[:k, :k] = np.triu(t11)
        t[k:] = 0.0
    return UTV(mat, t, v, k, mat.passes)


def right(mat: Tall, b: int, q: int, k: int, seed: int, draw, tol: float) -> UTV:
    n = mat.n
    v, t = np.eye(n), np.zeros((n, n))
    now, written, done, passes = mat, 0, 0, 0
    for s in range(0, k, b):
        w = min(b, n - s)
        e = s + w
        wv, cv = np.zeros((n - s, 0)), np.zeros((0, 0))
        if e < n:
            y = now.reduce(lambda ids, a, s=s, w=w: draw(seed, ids, w, s).T @ a[:, s:]).T
            for _ in range(q):
                x = np.linalg.qr(y)[0]
                y = now.reduce(lambda _, a, x=x, s=s: a[:, s:].T @ (a[:, s:] @ x))
            _, wv, cv = K.reflectors(y)

        def turn(a, s=s, wv=wv, cv=cv):
            out = a.copy()
            out[:, s:] = K.apply_right(wv, cv, a[:, s:])
            return out

        v, t = turn(v), turn(t)
        r = K.positive(now.reduce(lambda _, a, s=s, e=e, turn=turn: K.r_only(turn(a)[:, s:e]), K.r_only))
        d = np.abs(np.diag(r))
        x, sv, z = K.small_svd(r)
        v[:, s:e], t[:s, s:e] = v[:, s:e] @ z, t[:s, s:e] @ z
        lost = d.min() <= tol * max(t[0, 0], sv[0])
        keep = w if not lost else int((sv > tol * max(t[0, 0], sv[0])).sum())

        def basis(a, s=s, e=e, turn=turn, z=z, sv=sv, keep=keep):
            full = turn(a)
            full[:, s:e] = full[:, s:e] @ z
            return full, full[:, s : s + keep] / sv[:keep]

        rows = now.reduce(lambda _, a, basis=basis: (lambda f, u: u.T @ f)(*basis(a)))
        t[s : s + keep] = 0.0
        t[s : s + keep, e:] = rows[:, e:]
        t[range(s, s + keep), range(s, s + keep)] = sv[:keep]
        done = s + keep
        if lost or e >= k or e >= n:
            break

        def update(_, a, basis=basis, rows=rows, e=e):
            full, u = basis(a)
            out = full - u @ rows
            out[:, :e] = 0.0
            return out

        passes += now.passes if now is not mat else 0
        now = Tall(write_step(now.map_rows(update), "turned"), n)
        now.passes, written = 1, written + 1
    mat.passes += passes + (now.passes if now is not mat else 0)
    k = min(k, done)
    t[k:] = 0.0
    return UTV(mat, t, v, k, mat.passes, written)
