"""Unpivoted QR by panels with Householder reflectors, left-looking, on an immutable row frame; implicit and explicit Q.

The first k rows (by row_id) carry the triangle. A panel is made current by the compact product of all earlier reflectors, I - W T W', its
tall part is triangularized by a tree, twice, so that its thin basis is orthogonal to working precision, and the
reflectors are read off that basis and its top rows. A row of W depends on its row of A and on small arrays alone, so W is never
needed as a table during the run: a pass replays the steps on its rows. ``reflectors`` writes W (a panel of m x b a step,
partitioned by step), ``q`` forms thin Q by applying the reflectors backwards to the first columns of the identity.

Unlike A R^-1, this Q is orthogonal however ill-conditioned A is.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilerank.functions import kernels as K

from .matrix import Tall
from .sketchqr import low


@dataclass
class Step:
    """One panel: its columns in A, C = W'A_panel of the earlier W, the triangle of its tall part and that of the basis this
    gives (taken off it in a second solve, since their product would bring the first one's error back), and how W comes from the basis."""

    lo: int
    columns: list[int]
    c: np.ndarray
    tri: np.ndarray
    twice: np.ndarray | None = None
    signs: np.ndarray | None = None
    u0: np.ndarray | None = None


@dataclass
class Replay:
    """The finished steps, as they travel to the executors: ids of the first rows, steps, their S, and T of the compact product."""

    top: np.ndarray
    steps: list[Step] = field(default_factory=list)
    s: list[np.ndarray] = field(default_factory=list)
    t: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))

    def place(self, ids: np.ndarray) -> np.ndarray:
        """Index among the first rows, or their number for any other row."""
        k = len(self.top)
        at = np.searchsorted(self.top, ids)
        return np.where((at < k) & (self.top[np.minimum(at, k - 1)] == ids), at, k)

    def current(self, step: Step, a: np.ndarray, w: np.ndarray) -> np.ndarray:
        """The step's panel of these rows with all earlier reflectors applied."""
        t = self.t[: step.lo, : step.lo]
        return a[:, step.columns] - w[:, : step.lo] @ (t.T @ step.c)

    def basis(self, step: Step, h: np.ndarray, place: np.ndarray) -> np.ndarray:
        """Rows of the panel's thin basis; rows above it have none."""
        out = K.right_solve(h, step.tri)
        out = out if step.twice is None else K.right_solve(out, step.twice)
        out[place < step.lo] = 0.0
        return out

    def w_rows(self, ids: np.ndarray, a: np.ndarray) -> np.ndarray:
        """Rows of W, by replaying the finished steps."""
        place = self.place(ids)
        w = np.zeros((len(a), sum(len(s.columns) for s in self.steps)))
        for s in self.steps:
            hi = s.lo + len(s.columns)
            q = self.basis(s, self.current(s, a, w), place)
            own = np.flatnonzero((place >= s.lo) & (place < hi))
            q[own, place[own] - s.lo] -= s.signs[place[own] - s.lo]
            w[:, s.lo : hi] = K.right_solve(q, s.u0)
        return w

    def at_top(self, ids: np.ndarray, x: np.ndarray) -> np.ndarray:
        """The first rows among these, at their places; zero elsewhere."""
        place = self.place(ids)
        out = np.zeros((len(self.top), x.shape[1]))
        own = place < len(self.top)
        out[place[own]] = x[own]
        return out


@dataclass
class ReflectorQR:
    """``r``: triangle of the columns; W and Q on demand."""

    mat: Tall
    columns: list[int]
    run: Replay
    r: np.ndarray

    def reflectors(self) -> DataFrame:
        """W as (step, row_id, w): a panel of vectors a step, for ``write.partitionBy("step")``."""
        sizes = [(i, s.lo, len(s.columns)) for i, s in enumerate(self.run.steps)]
        rows = self.mat.map_rows(self.run.w_rows)
        parts = F.array(*[F.struct(F.lit(i).alias("step"), F.slice("x", lo + 1, n).alias("w")) for i, lo, n in sizes])
        return rows.select("row_id", F.explode(parts).alias("p")).select("p.step", "row_id", "p.w")

    def back_accumulated(self) -> np.ndarray:
        """M with thin Q = E - W M: the reflectors applied from the last to the first to E, the first columns of the identity."""
        k, run = len(self.columns), self.run

        def sums(ids, a):
            w = run.w_rows(ids, a)
            return np.vstack([w.T @ w, run.at_top(ids, w)])

        both = self.mat.reduce(sums)
        gram, top = both[:k], both[k:]
        m = np.zeros((k, k))
        for step, s in reversed(list(zip(run.steps, run.s, strict=True))):
            lo, hi = step.lo, step.lo + len(step.columns)
            m[lo:hi] += s @ (top[:, lo:hi].T - gram[lo:hi] @ m)
        return m

    def q(self) -> DataFrame:
        """Thin Q as a row frame."""
        m, k, run = self.back_accumulated(), len(self.columns), self.run

        def rows(ids, a):
            out = -run.w_rows(ids, a) @ m
            place = run.place(ids)
            own = np.flatnonzero(place < k)
            out[own, place[own]] += 1.0
            return out

        return self.mat.map_rows(rows)


def apply_q(f: ReflectorQR, x: np.ndarray) -> DataFrame:
    """Q X for a small X (as many rows as columns were factored): a row frame."""
    return Tall(f.q(), len(f.columns)).times(x)


def apply_qt(f: ReflectorQR, y: DataFrame, width: int) -> np.ndarray:
    """Q'Y for a row frame Y over the same rows."""
    k = len(f.columns)
    both = f.q().select("row_id", F.col("x").alias("q")).join(y.select("row_id", F.col("x").alias("y")), "row_id").select("row_id", F.concat("q", "y").alias("x"))
    return Tall(both, k + width).reduce(lambda _, a: a[:, :k].T @ a[:, k:])


def reflector_qr(mat: Tall, b: int, columns: list[int] | None = None) -> ReflectorQR:
    """QR of the columns, in the order given. Row ids must differ; there must be as many rows as columns."""
    columns = list(range(mat.n)) if columns is None else list(columns)
    k = len(columns)
    top = np.array(sorted(r["row_id"] for r in mat.df.select("row_id").orderBy("row_id").limit(k).collect()))  # k numbers
    if len(top) < k or len(set(top.tolist())) < k:
        raise ValueError("needs as many rows of different ids as columns")
    f, r = Replay(top), np.zeros((k, k))
    for lo in range(0, k, b):
        step = Step(lo, columns[lo : lo + b], np.zeros((lo, len(columns[lo : lo + b]))), np.zeros((0, 0)))
        n, prior = len(step.columns), f.steps[-1].lo if f.steps else 0

        def products(ids, a, step=step, prior=prior):
            # earlier reflectors with the panel, and with the last ones, which the compact product still lacks
            w = f.w_rows(ids, a)
            return w.T @ np.hstack([a[:, step.columns], w[:, prior:]])

        if lo:
            both = mat.reduce(products)
            step.c, cross, s = both[:, :n], both[:prior, n:], f.s[-1]
            t = np.zeros((lo, lo))
            t[:prior, :prior], t[prior:, prior:] = f.t, s
            t[:prior, prior:] = -f.t @ cross @ s
            f.t = t

        def tall(ids, a, step=step, n=n):
            place = f.place(ids)
            h = f.current(step, a, f.w_rows(ids, a))
            above = np.zeros((step.lo, n))
            own = place < step.lo
            above[place[own]] = h[own]
            h[own] = 0.0
            return np.vstack([above, low(K.r_only(h), n)])

        def merge(x, y, lo=lo):
            return np.vstack([x[:lo] + y[:lo], K.r_only(x[lo:], y[lo:])])

        got = mat.reduce(tall, merge)
        above, tri = got[:lo], K.positive(got[lo:])
        if np.abs(np.diag(tri)).min() <= 1e-15 * max(np.linalg.norm(got), 1e-300):
            raise ValueError("a panel has dependent columns; choose them by pivoting first")
        step.tri = tri

        def again(ids, a, step=step, n=n):
            place = f.place(ids)
            q = f.basis(step, f.current(step, a, f.w_rows(ids, a)), place)
            head = np.zeros((n, n))
            own = np.flatnonzero((place >= step.lo) & (place < step.lo + n))
            head[place[own] - step.lo] = q[own]
            return np.vstack([head, low(K.r_only(q), n)])

        got = mat.reduce(again, lambda x, y, n=n: np.vstack([x[:n] + y[:n], K.r_only(x[n:], y[n:])]))
        step.twice = K.positive(got[n:])
        step.signs, step.u0, s = K.reconstruct(K.right_solve(got[:n], step.twice))
        f.s.append(s)
        f.steps.append(step)
        # I - W S W' sends the panel to its basis times the signs
        r[:lo, lo : lo + n], r[lo : lo + n, lo : lo + n] = above, step.signs[:, None] * (step.twice @ tri)
    return ReflectorQR(mat, columns, f, r)
