import numpy as np
import pytest

from tilerank.functions import kernels as K
from tilerank.functions import keyed

rng = np.random.default_rng(0)
SHAPES = [(1, 1), (3, 3), (9, 3), (3, 5), (20, 7), (8, 1)]


@pytest.mark.parametrize("shape", SHAPES)
def test_reflectors_and_applies(shape):
    for a in (rng.normal(size=shape), np.zeros(shape), np.ones(shape)):
        r, w, s = K.reflectors(a)
        q = np.eye(len(a)) - w @ s @ w.T
        assert np.allclose(q @ q.T, np.eye(len(a))) and np.allclose(q @ r, a)
        x = rng.normal(size=(len(a), 4))
        assert np.allclose(K.apply_left(w, s, x), q.T @ x) and np.allclose(K.apply_right(w, s, x.T), x.T @ q)


def test_stacked_pairs():
    r, d, top, low = np.triu(rng.normal(size=(4, 4))), rng.normal(size=(6, 4)), rng.normal(size=(4, 3)), rng.normal(size=(6, 3))
    t, w, s = K.stacked(r, d)
    q = np.eye(10) - w @ s @ w.T
    assert np.allclose(q.T @ np.vstack([r, d]), np.vstack([t, np.zeros((6, 4))]))
    assert np.allclose(np.vstack(K.stacked_left(w, s, top, low)), q.T @ np.vstack([top, low]))
    assert np.allclose(np.hstack(K.stacked_right(w, s, top.T, low.T)), np.hstack([top.T, low.T]) @ q)


@pytest.mark.parametrize("shape", SHAPES)
def test_pivoted(shape):
    a = rng.normal(size=shape)
    p, r = K.pivoted(a)
    assert sorted(p) == list(range(shape[1])) and np.allclose(r.T @ r, a[:, p].T @ a[:, p])
    d = np.abs(np.diag(r))
    assert all(x >= y - 1e-12 for x, y in zip(d, d[1:]))
    assert K.pivoted(np.ones((4, 3)))[0][0] == 0


def test_reconstruct():
    for a in (rng.normal(size=(9, 4)), np.eye(9, 4)):
        q = np.linalg.qr(a)[0]
        signs, u0, s = K.reconstruct(q[:4])
        w = q.copy()
        w[:4] -= np.diag(signs)
        w = K.right_solve(w, u0)
        h = np.eye(9) - w @ s @ w.T
        assert np.allclose(h @ h.T, np.eye(9)) and np.allclose(h[:, :4], q * signs)


@pytest.mark.parametrize("shape", [(12, 12), (20, 7), (9, 9), (30, 10), (5, 1)])
@pytest.mark.parametrize("q", [0, 1, 2])
@pytest.mark.parametrize("b", [1, 3, 4, 50])
def test_utv(shape, q, b):
    a = rng.normal(size=shape)
    u, t, v = K.utv(a, b, q, rng.normal(size=shape))
    n = shape[1]
    assert np.allclose(u @ t @ v.T, a) and np.allclose(u.T @ u, np.eye(len(a))) and np.allclose(v.T @ v, np.eye(n))
    assert np.allclose(np.tril(t, -1), 0)
    for s in range(0, n, b):
        d = np.diag(t)[s : s + b]
        assert (d >= 0).all() and (np.diff(d) <= 1e-12).all() and np.allclose(t[s : s + len(d), s : s + len(d)], np.diag(d))


def test_solves():
    r, b = np.triu(rng.normal(size=(5, 5))) + 3 * np.eye(5), rng.normal(size=(5, 2))
    assert np.allclose(r @ K.solve_upper(r, b), b) and np.allclose(K.right_solve(b.T, r) @ r, b.T)


def test_keyed_draws_are_normal_and_repeat():
    for f in keyed.DRAWS.values():
        g = f(3, np.arange(300), 8)
        assert abs(g.mean()) < 0.08 and abs(g.std() - 1) < 0.05
        assert np.array_equal(f(3, np.arange(5), 4, 2), g[:5, 2:6])
