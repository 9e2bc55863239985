"""Blocked column-pivoted QR steered by small Gaussian sketches, for tall matrices on an immutable row frame.

The thin orthogonal factor is not stored: with the triangle R11 of the chosen columns P, a row of Q is the row's chosen
entries times R11^-1, so "bring up to date" is row-local. A step makes its panel current, H = A_new - A_P (R11^-1 R_new), and
gathers H'A and the triangle R22 of H in one pass; R22^-T H'A are the new rows of R for all columns. A step costs a multiple of m n b
flops whatever was chosen before, and a partial run never touches more than that. Where H has kept a part along Q (cancellation)
the step's pass is repeated with that part taken off. ``reflect`` stores reflectors instead.

Schedules and sketches:

* ``left`` with ``pullback``: H = G - Q (Q'G), then Y = H'A (two passes a step);
* ``left`` with ``recompute``: the rows are updated on the fly, A - Q (Q'A), and multiplied by G;
* ``left`` with ``project``: the next sketch G'A comes with the step's pass and is projected by the known rows of R;
* ``left`` with ``upfront``: all sketches G'A in one pass, each projected by the known rows of R;
* ``left`` with ``downdate``: one sketch for all steps, downdated by the finished rows;
* ``right``: the trailing matrix is updated and written as a new table at each step; ``layout`` ``virtual`` leaves the columns
  where they stand (R P' comes out), ``physical`` moves them into pivot order as it writes, and drops the finished ones;
* ``triangle``: one pass makes the triangle of [A | G]; the rest runs on it on the driver.

All but ``downdate`` use the same draws and choose the same pivots.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame

from tilerank.functions import kernels as K
from tilerank.functions.keyed import DRAWS

from .matrix import Tall, write_step

#: A residual below this share of the norm is measured by a pass of its own, as the difference of squares has lost its digits.
CANCELLED = 1e-5
#: A panel that keeps more than this share of itself along the finished columns is made current again.
KEPT = 1e-9


@dataclass
class PivotedQR:
    """``perm``: chosen columns first, then the rest in order; ``r``: k x n, columns in the order of ``perm``."""

    mat: Tall
    perm: list[int]
    r: np.ndarray
    k: int
    residual: float
    passes: int
    written: int = 0
    steps: list = field(default_factory=list)

    def q(self) -> DataFrame:
        """Thin Q as a row frame, formed on demand."""
        chosen, r11 = self.perm[: self.k], self.r[:, : self.k]
        return self.mat.map_rows(lambda _, a: K.right_solve(a[:, chosen], r11))

    def virtual(self) -> np.ndarray:
        """R P': columns where they stood."""
        out = np.empty_like(self.r)
        out[:, self.perm] = self.r
        return out

    def reconstruct(self) -> DataFrame:
        """The rank-k approximation as a row frame."""
        chosen, mix = self.perm[: self.k], K.solve_upper(self.r[:, : self.k], self.virtual())
        return self.mat.map_rows(lambda _, a: a[:, chosen] @ mix)

    def physical(self) -> DataFrame:
        """A with its columns moved into pivot order."""
        perm = self.perm
        return self.mat.map_rows(lambda _, a: a[:, perm])


class Run:
    """What a left-looking run knows: chosen columns, their triangle, and the rows of R for all columns, where they stand."""

    def __init__(self, mat: Tall, tol: float):
        self.mat, self.tol = mat, tol
        self.chosen: list[int] = []
        self.r11, self.rows = np.zeros((0, 0)), np.zeros((0, mat.n))
        self.scale: float | None = None
        self.norms: np.ndarray | None = None
        self.extra: np.ndarray | None = None
        self.steps: list = []

    def first_pass(self, draw) -> np.ndarray:
        """G'A and the squared column norms."""
        both = self.mat.reduce(lambda ids, a: np.vstack([draw(ids).T @ a, (a * a).sum(0)]))
        self.norms = both[-1]
        return both[:-1]

    def project(self, s: np.ndarray) -> np.ndarray:
        """The sketch of A less its part along Q: S - S_P R11^-1 R."""
        return s - K.right_solve(s[:, self.chosen], self.r11) @ self.rows

    def panel(self, picked: list[int], more=None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray | None]:
        """Make the picked columns current: (rows of R over the panel, its triangle, H'A, ``more`` (ids)'A), in one pass or few."""
        p, b = list(self.chosen), len(picked)
        over = self.rows[:, picked].copy()

        def combine(x: np.ndarray, y: np.ndarray) -> np.ndarray:
            out = x + y
            out[b : 2 * b, :b] = low(K.r_only(x[b : 2 * b, :b], y[b : 2 * b, :b]), b)
            return out

        for _ in range(3):
            w = K.solve_upper(self.r11, over)

            def local(ids, a, w=w):
                h = a[:, picked] - a[:, p] @ w
                tri = np.zeros((b, a.shape[1]))
                tri[:, :b] = low(K.r_only(h), b)
                parts = [h.T @ a, tri]
                return np.vstack(parts if more is None else [*parts, more(ids).T @ a])

            got = self.mat.reduce(local, combine)
            across, tri, extra = got[:b], K.positive(got[b : 2 * b, :b]), got[2 * b :] if more is not None else None
            kept = np.linalg.solve(self.r11.T, across[:, p].T) if p else np.zeros((0, b))
            if np.linalg.norm(kept) <= KEPT * np.linalg.norm(tri):
                break
            over = over + kept
        return over, tri, across, extra

    def take(self, picked: list[int], over: np.ndarray, tri: np.ndarray, across: np.ndarray) -> bool:
        """Add the panel's columns, up to the first that depends on those before; whether all were taken."""
        d = np.abs(np.diag(tri))
        self.scale = d.max() if self.scale is None else self.scale
        good = next((i for i in range(len(d)) if d[i] <= self.tol * self.scale), len(d))
        new = np.linalg.solve(tri[:good, :good].T, across[:good]) if good else np.zeros((0, self.mat.n))
        new[:, self.chosen] = 0.0
        new[:, picked[:good]] = tri[:good, :good]
        k = len(self.chosen)
        r11 = np.zeros((k + good, k + good))
        r11[:k, :k], r11[:k, k:], r11[k:, k:] = self.r11, over[:, :good], tri[:good, :good]
        self.rows[:, picked] = over
        self.r11, self.rows, self.chosen = r11, np.vstack([self.rows, new]), self.chosen + picked[:good]
        self.steps.append({"step": len(self.steps), "pivots": picked[:good], "r": d[:good].tolist(), "passes": self.mat.passes, "residual": self.residual()})
        return good == len(d)

    def residual(self) -> float:
        """Norm of what is left, from the difference of squares."""
        left = self.norms - (self.rows**2).sum(0)
        left[self.chosen] = 0.0
        return float(np.sqrt(np.maximum(left, 0.0).sum()))

    def result(self, written: int = 0) -> PivotedQR:
        chosen, k = self.chosen, len(self.chosen)
        done = set(chosen)
        perm = chosen + [j for j in range(self.mat.n) if j not in done]
        residual = self.residual()
        if k < self.mat.n and residual <= CANCELLED * np.sqrt(self.norms.sum()):
            mix = K.solve_upper(self.r11, self.rows)
            residual = float(np.sqrt(self.mat.reduce(lambda _, a: np.array([[((a - a[:, chosen] @ mix) ** 2).sum()]]))[0, 0]))
        r = self.rows[:, perm]
        r[:, :k] = self.r11
        return PivotedQR(self.mat, perm, r, k, residual, self.mat.passes, written, self.steps)


def low(r: np.ndarray, b: int) -> np.ndarray:
    """A triangle with zero rows below, to b of them."""
    return r if len(r) == b else np.vstack([r, np.zeros((b - len(r), r.shape[1]))])


def sketch_qr(
    mat: Tall, b: int, k: int | None = None, schedule: str = "left", sketch: str = "pullback", seed: int = 7, rng: str = "md5", tol: float = 1e-10,
    oversample: int = 0, error: float = 0.0, layout: str = "virtual",
) -> PivotedQR:
    """Pivoted QR of k columns in blocks of b. It stops before that where columns depend on the chosen ones (``tol`` of the
    first pivot), or as soon as the residual's Frobenius norm is at most ``error`` times that of A."""
    n = mat.n
    k = n if k is None else min(k, n)
    if b < 1:
        raise ValueError("a block has one column at least")
    b = min(b, k)
    draw = DRAWS[rng]
    if schedule == "triangle":
        return on_triangle(mat, b, k, seed, draw, tol, error)
    if schedule == "right":
        return right_looking(mat, b, k, seed, draw, tol, error, layout)
    if schedule != "left":
        raise ValueError(f"no schedule {schedule}")
    if sketch not in ("pullback", "recompute", "project", "upfront", "downdate"):
        raise ValueError(f"no sketch {sketch}")
    run = Run(mat, tol)
    width = {"upfront": k, "downdate": b + oversample}.get(sketch, b)
    first = run.first_pass(lambda ids: draw(seed, ids, width))
    ahead = first
    for lo in range(0, k, b):
        w = min(b, k - lo)

        def gamma(ids, at=lo, w=w):
            return draw(seed, ids, w, at)

        p, r11 = list(run.chosen), run.r11
        if sketch == "upfront":
            y = run.project(first[lo : lo + w])
        elif sketch == "downdate":
            y = run.project(first)
        elif not p:
            y = first[:w]
        elif sketch == "project":
            y = run.project(ahead)
        elif sketch == "recompute":
            mix = K.solve_upper(r11, run.rows)
            y = mat.reduce(lambda ids, a, mix=mix: gamma(ids).T @ (a - a[:, p] @ mix))
        else:
            c = mat.reduce(lambda ids, a: a[:, p].T @ gamma(ids))
            z = K.solve_upper(r11, np.linalg.solve(r11.T, c))
            y = mat.reduce(lambda ids, a, z=z: (gamma(ids) - a[:, p] @ z).T @ a)
        rest = [j for j in range(n) if j not in set(p)]
        order, _ = K.pivoted(y[:, rest], w)
        picked = [rest[j] for j in order[:w]]
        more = None
        if sketch == "project" and lo + w < k:
            more = lambda ids, at=lo + w, c=min(b, k - lo - w): draw(seed, ids, c, at)
        over, tri, across, ahead = run.panel(picked, more)
        if not run.take(picked, over, tri, across) or run.steps[-1]["residual"] <= error * np.sqrt(run.norms.sum()):
            break
    return run.result()


def on_triangle(mat: Tall, b: int, k: int, seed: int, draw, tol: float, error: float = 0.0) -> PivotedQR:
    """One pass over A; sketches come from the triangle of [A | G] since the rotation is the same."""
    n = mat.n
    whole = mat.triangle(None, lambda ids: draw(seed, ids, k))
    t, g = whole[:, :n].copy(), whole[:, n:].copy()
    order, steps = list(range(n)), []
    scale, k_done, norm = None, 0, np.linalg.norm(t)
    for lo in range(0, k, b):
        w = min(b, k - lo)
        y = g[lo:, lo : lo + w].T @ t[lo:, lo:]
        local, _ = K.pivoted(y, w)
        order[lo:] = [order[lo + j] for j in local]
        t[:, lo:] = t[:, [lo + j for j in local]]
        r, wy, s = K.reflectors(t[lo:, lo : lo + w])
        t[lo:, lo + w :], g[lo:] = K.apply_left(wy, s, t[lo:, lo + w :]), K.apply_left(wy, s, g[lo:])
        t[lo:, lo : lo + w] = r
        d = np.abs(np.diag(t))[lo : lo + w]
        scale = d.max() if scale is None else scale
        good = next((i for i in range(w) if d[i] <= tol * scale), w)
        k_done = lo + good
        steps.append({"step": lo // b, "pivots": order[lo : lo + good], "r": d[:good].tolist(), "passes": mat.passes, "residual": float(np.linalg.norm(t[k_done:, k_done:]))})
        if good < w or steps[-1]["residual"] <= error * norm:
            break
    r = K.positive(t[:k_done])
    tail = np.argsort(order[k_done:], kind="stable")
    r = np.hstack([r[:, :k_done], r[:, k_done:][:, tail]])
    return PivotedQR(mat, order[:k_done] + sorted(order[k_done:]), r, k_done, float(np.linalg.norm(t[k_done:, k_done:])), mat.passes, 0, steps)


def right_looking(mat: Tall, b: int, k: int, seed: int, draw, tol: float, error: float = 0.0, layout: str = "virtual") -> PivotedQR:
    """Each step writes the whole updated matrix anew, and the draws beside it.

    ``virtual``: columns stay where they are, the finished ones hold zeros. ``physical``: a step's write puts the remaining columns in order
    and leaves the finished ones out, their part of R being known.
    """
    if layout not in ("virtual", "physical"):
        raise ValueError(f"no layout {layout}")
    n, steps, written, scale = mat.n, [], 0, None
    width = n  # columns of the trailing table that belong to A
    at = list(range(n))  # and the columns of A that they are
    chosen: list[int] = []
    rows = np.zeros((0, n))
    trailing = Tall(mat.map_rows(lambda ids, a: np.hstack([a, draw(seed, ids, k)])), n + k)
    norms = None
    for lo in range(0, k, b):
        w = min(b, k - lo)
        y = trailing.reduce(lambda _, a, lo=lo, w=w, c=width: np.vstack([a[:, c + lo : c + lo + w].T @ a[:, :c], (a[:, :c] ** 2).sum(0)]))
        norms = y[-1] if norms is None else norms
        rest = [j for j in range(width) if at[j] not in set(chosen)]
        order, _ = K.pivoted(y[:-1][:, rest], w)
        picked = [rest[j] for j in order[:w]]
        tri, across = trailing_panel(trailing, picked)
        d = np.abs(np.diag(tri))
        scale = d.max() if scale is None else scale
        good = next((i for i in range(w) if d[i] <= tol * scale), w)
        picked, tri = picked[:good], tri[:good, :good]
        z = np.linalg.solve(tri.T, across[:good]) if good else across[:0]
        z[:, picked] = tri
        new = np.zeros((good, n))
        new[:, at] = z[:, :width]
        new[:, chosen] = 0.0
        chosen, rows = chosen + [at[j] for j in picked], np.vstack([rows, new])
        residual = float(np.sqrt(max(0.0, norms.sum() - (rows**2).sum())))
        steps.append({"step": lo // b, "pivots": [at[j] for j in picked], "r": d[:good].tolist(), "passes": mat.passes + trailing.passes, "residual": residual})
        if good < w or len(chosen) >= k or residual <= error * np.sqrt(norms.sum()):
            break
        mix = K.solve_upper(tri, z)
        stay = None if layout == "virtual" else [j for j in range(width + k) if j not in set(picked)]

        def update(_, a, p=picked, mix=mix, stay=stay):
            out = a - a[:, p] @ mix
            out[:, p] = 0.0
            return out if stay is None else out[:, stay]

        done = trailing.passes
        if stay is not None:
            at = [at[j] for j in stay if j < width]
            width -= good
        trailing = Tall(write_step(trailing.map_rows(update), "trailing"), width + k)
        trailing.passes, written = done + 1, written + 1
    mat.passes += trailing.passes
    if layout == "virtual":
        at = [j for j in range(n) if j not in set(chosen)]
    else:
        at = [j for j in at if j not in set(chosen)]
    perm = chosen + at
    k = len(chosen)
    r = rows[:, perm]
    r[:, :k] = np.triu(r[:, :k])
    return PivotedQR(mat, perm, r, k, residual if k < n else 0.0, mat.passes, written, steps)


def trailing_panel(trailing: Tall, picked: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Triangle of some columns and their products with all, in one pass."""
    b = len(picked)

    def local(_, a):
        h = a[:, picked]
        tri = np.zeros((b, a.shape[1]))
        tri[:, :b] = low(K.r_only(h), b)
        return np.vstack([h.T @ a, tri])

    def combine(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        out = x + y
        out[b:, :b] = low(K.r_only(x[b:, :b], y[b:, :b]), b)
        return out

    got = trailing.reduce(local, combine)
    return K.positive(got[b:, :b]), got[:b]


def pivoted_qr(mat: Tall, k: int | None = None) -> PivotedQR:
    """Classical column pivoting, on the triangle that one pass gives."""
    r = mat.triangle()
    order, t = K.pivoted(r, k)
    k = min(len(t), mat.n if k is None else k)
    t = K.positive(t)
    return PivotedQR(mat, order, t[:k], k, float(np.linalg.norm(t[k:, k:])), mat.passes)


def pivoted_columnwise(mat: Tall, k: int) -> PivotedQR:
    """Classical pivoting one column at a time: a pass for the norms of what is left, and one for the row of R, at every column."""
    run = Run(mat, 1e-14)
    run.first_pass(lambda ids: np.zeros((len(ids), 0)))
    for _ in range(min(k, mat.n)):
        p, mix = list(run.chosen), K.solve_upper(run.r11, run.rows)
        norms = np.array(mat.reduce(lambda _, a, p=p, mix=mix: ((a - a[:, p] @ mix) ** 2).sum(0)[None, :])[0]) if p else run.norms.copy()
        norms[p] = -1.0
        picked = [int(np.argmax(norms))]
        if not run.take(picked, *run.panel(picked)[:3]):
            break
    return run.result()


def left_qr(mat: Tall, b: int) -> np.ndarray:
    """Unpivoted QR by column panels, left-looking: a panel gets its rows of R from the finished panels (one pass), is brought up to
    date by them and triangularized (one pass); columns to its right are not touched."""
    n = mat.n
    out = np.zeros((n, n))
    for lo in range(0, n, b):
        hi = min(n, lo + b)
        r11 = out[:lo, :lo]
        over = np.linalg.solve(r11.T, mat.reduce(lambda _, a, lo=lo, hi=hi: a[:, :lo].T @ a[:, lo:hi])) if lo else np.zeros((0, hi - lo))
        for _ in range(3):
            w = K.solve_upper(r11, over)

            def local(_, a, lo=lo, hi=hi, w=w):
                h = a[:, lo:hi] - a[:, :lo] @ w
                return np.vstack([a[:, :lo].T @ h, low(K.r_only(h), hi - lo)])

            def combine(x, y, lo=lo):
                return np.vstack([x[:lo] + y[:lo], K.r_only(x[lo:], y[lo:])])

            got = mat.reduce(local, combine)
            tri = K.positive(got[lo:])
            kept = np.linalg.solve(r11.T, got[:lo]) if lo else got[:0]
            if np.linalg.norm(kept) <= KEPT * np.linalg.norm(tri):
                break
            over = over + kept
        out[:lo, lo:hi], out[lo:hi, lo:hi] = over, tri
    return out


def panel_qr(mat: Tall) -> np.ndarray:
    """Reduction-tree QR of all columns."""
    return mat.triangle()


def append_rows(r: np.ndarray, more: Tall) -> np.ndarray:
    """Triangle of rows already factored and further rows."""
    return K.positive(K.r_only(r, more.triangle()))


def numerical_rank(r: np.ndarray, tol: float = 1e-8) -> int:
    d = np.abs(np.diag(r))
    return int((d > tol * d.max()).sum()) if d.size and d.max() > 0 else 0
