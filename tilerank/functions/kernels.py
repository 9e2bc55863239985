"""Dense kernels on NumPy arrays: what one task does to one or two tiles. No Spark here."""

from __future__ import annotations

import numpy as np


def reflectors(a: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """QR of a tile in compact form: R (upper), W (unit lower trapezoid) and S with Q = I - W S W'."""
    r = np.array(a, float)
    m, n = r.shape
    k = min(m, n)
    w, s = np.zeros((m, k)), np.zeros((k, k))
    for j in range(k):
        x = r[j:, j]
        norm = np.linalg.norm(x)
        w[j, j] = 1.0
        if norm == 0.0:
            continue
        alpha = -np.copysign(norm, x[0])
        w[j + 1 :, j] = x[1:] / (x[0] - alpha)
        beta = (alpha - x[0]) / alpha
        v = w[j:, j]
        r[j:, j:] -= beta * np.outer(v, v @ r[j:, j:])
        s[j, j] = beta
        s[:j, j] = -beta * (s[:j, :j] @ (w[:, :j].T @ w[:, j]))
    return np.triu(r), w, s


def apply_left(w: np.ndarray, s: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Q' X for Q = I - W S W'."""
    return x - w @ (s.T @ (w.T @ x))


def apply_right(w: np.ndarray, s: np.ndarray, x: np.ndarray) -> np.ndarray:
    """X Q."""
    return x - ((x @ w) @ s) @ w.T


def stacked(r: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """QR of a triangle on top of a dense tile -> new triangle, W of both parts together, S."""
    made, w, s = reflectors(np.vstack([r, d]))
    return made[: len(r)], w, s


def stacked_left(w: np.ndarray, s: np.ndarray, top: np.ndarray, low: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    x = apply_left(w, s, np.vstack([top, low]))
    return x[: len(top)], x[len(top) :]


def stacked_right(w: np.ndarray, s: np.ndarray, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    x = apply_right(w, s, np.hstack([left, right]))
    return x[:, : left.shape[1]], x[:, left.shape[1] :]


def r_only(*parts: np.ndarray) -> np.ndarray:
    """Triangle of the stacked parts, at most n rows."""
    return np.linalg.qr(np.vstack(parts), mode="r")


def positive(r: np.ndarray) -> np.ndarray:
    """Rows signed so that the diagonal is not negative."""
    d = np.sign(np.diag(r))
    d[d == 0] = 1.0
    return r * np.append(d, np.ones(len(r) - len(d)))[:, None]


def pivoted(y: np.ndarray, steps: int | None = None) -> tuple[list[int], np.ndarray]:
    """Greedy column-pivoted QR: pivots of the first ``steps`` and R with its columns in pivot order.

    Ties go to the smallest column. Norms are downdated and taken anew when they lost half of their digits.
    """
    r = np.array(y, float)
    m, n = r.shape
    steps = min(m, n) if steps is None else min(steps, m, n)
    order = list(range(n))
    norms = (r * r).sum(0)
    fresh = norms.copy()
    for k in range(steps):
        rest = norms[k:]
        top = rest.max()
        j = k + min((i for i in range(n - k) if rest[i] == top), key=lambda i: order[k + i])
        if j != k:
            r[:, [k, j]] = r[:, [j, k]]
            order[k], order[j] = order[j], order[k]
            norms[[k, j]], fresh[[k, j]] = norms[[j, k]], fresh[[j, k]]
        tri, w, s = reflectors(r[k:, k : k + 1])
        r[k:, k:] = apply_left(w, s, r[k:, k:])
        r[k + 1 :, k] = 0.0
        norms[k + 1 :] -= r[k, k + 1 :] ** 2
        lost = np.flatnonzero(norms[k + 1 :] <= 1e-8 * fresh[k + 1 :]) + k + 1
        if len(lost):
            norms[lost] = fresh[lost] = (r[k + 1 :, lost] ** 2).sum(0)
    return order, np.triu(r)


def solve_upper(r: np.ndarray, b: np.ndarray) -> np.ndarray:
    """R^-1 B by back substitution."""
    x = np.array(b, float)
    for i in range(len(r) - 1, -1, -1):
        x[i] = (x[i] - r[i, i + 1 :] @ x[i + 1 :]) / r[i, i]
    return x


def right_solve(x: np.ndarray, r: np.ndarray) -> np.ndarray:
    """X R^-1 for upper R, column by column."""
    out = np.array(x, float)
    for j in range(r.shape[1]):
        out[:, j] = (out[:, j] - out[:, :j] @ r[:j, j]) / r[j, j]
    return out


def reconstruct(top: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """From the first b rows of a thin Q: signs, U0 and S such that W = (Q - [diag(signs); 0]) U0^-1 gives
    I - W S W' with first columns Q diag(signs). A signed LU without pivoting."""
    b = top.shape[1]
    x = np.array(top, float)
    signs, low = np.zeros(b), np.eye(b)
    for j in range(b):
        signs[j] = -1.0 if x[j, j] >= 0 else 1.0
        x[j, j] -= signs[j]
        low[j + 1 :, j] = x[j + 1 :, j] / x[j, j]
        x[j + 1 :] -= np.outer(low[j + 1 :, j], x[j])
    u0 = np.triu(x)
    s = -u0 @ np.diag(signs) @ np.linalg.inv(low).T
    return signs, u0, s


def small_svd(t: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """u, d, v of a tile; the largest entry of each column of u is positive."""
    u, d, vt = np.linalg.svd(t)
    k = len(d)
    flip = np.sign(u[np.abs(u[:, :k]).argmax(0), np.arange(k)])
    u[:, :k] *= flip
    vt[:k] *= flip[:, None]
    return u, d, vt.T


def utv(a: np.ndarray, b: int, q: int, gamma: np.ndarray, k: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Blocked randomized UTV in memory: U, T, V with A = U T V'. ``gamma`` holds the Gaussian columns of all steps; it
    receives the left reflectors, so that its trailing rows are a fresh draw at each step.

    Each step turns the trailing columns toward the leading right directions (sketch and q power steps), triangularizes
    the next panel from the left, and makes its diagonal tile diagonal. All rows of T get the right factor.
    """
    t, g = np.array(a, float), np.array(gamma, float)
    m, n = t.shape
    u, v = np.eye(m), np.eye(n)
    for s in range(0, min(n, m) if k is None else min(k, n, m), b):
        w_ = min(b, n - s)
        e = s + w_
        if e < n:
            y = t[s:, s:].T @ g[s:, s : s + w_]
            for _ in range(q):
                y = t[s:, s:].T @ (t[s:, s:] @ np.linalg.qr(y)[0])
            _, w, c = reflectors(y)
            t[:, s:], v[:, s:] = apply_right(w, c, t[:, s:]), apply_right(w, c, v[:, s:])
        if m - s > w_ or e < n:
            r, w, c = reflectors(t[s:, s:e])
            t[s:, e:], g[s:] = apply_left(w, c, t[s:, e:]), apply_left(w, c, g[s:])
            u[:, s:] = apply_right(w, c, u[:, s:])
            t[s:, s:e] = r
        h = min(w_, m - s)
        x, d, z = small_svd(t[s : s + h, s:e])
        t[s : s + h, s:e] = 0.0
        t[s + np.arange(len(d)), s + np.arange(len(d))] = d
        t[:s, s:e], v[:, s:e] = t[:s, s:e] @ z, v[:, s:e] @ z
        t[s : s + h, e:], u[:, s : s + h] = x.T @ t[s : s + h, e:], u[:, s : s + h] @ x
    return u, t, v
