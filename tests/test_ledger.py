import numpy as np
import pytest

from tilerank.functions import kernels as K
from tilerank.operators import tiles as X
from tilerank.plans import costmodel as C
from tilerank.plans import ledger as L


def test_two_by_two():
    t = L.plan_utv(2, 2)
    assert len(t) == 22 and L.totals(L.replay(t, "direct"), 6) == (10, 6) and L.totals(L.replay(t, "direct")) == (44, 35)
    assert L.totals(L.replay(t, "lru", 7), 6) == (4, 0) == L.totals(L.replay(t, "overlap", 7), 6)
    for pin in (True, False):
        trace = L.replay(t, "lru", 7, pin)
        assert L.totals(trace) == (9, 8) and trace[-1]["dirty"] == 7
        assert L.totals(L.replay(t, "lru", 8, pin)) == (7, 6) and L.totals(L.replay(t, "lru", 16, pin)) == (4, 0)
    assert [L.totals(L.replay(t, "lru", s, True)) for s in (5, 6)] == [(16, 15), (9, 9)]
    assert [L.totals(L.replay(t, "lru", s, False)) for s in (5, 6)] == [(19, 17), (10, 9)]


def test_overlap_hides_the_smaller_part():
    t = L.plan_utv(5, 5, 1)
    for t_io, t_flop in ((0.1, 1.0), (1.0, 0.1), (1.0, 0.5)):
        a, b, c = (L.makespan(t, m, 20, t_io, t_flop, 4) for m in ("direct", "lru", "overlap"))
        assert a["real"] > b["real"] > c["real"] >= max(c["compute"] / 4, c["io"]) - 1e-9


def test_first_column_counts():
    assert len([t for t in L.plan_qr(3, 3) if t.step == 0]) == 9
    for m, n in ((4, 4), (6, 3)):
        assert len([t for t in L.plan_qr(m, n) if t.step == 0]) == n + (m - 1) * n


@pytest.mark.parametrize("m,n,b", [(12, 12, 4), (20, 8, 4), (10, 7, 3), (9, 9, 3), (6, 6, 6), (13, 5, 4), (24, 20, 8), (6, 5, 6)])
@pytest.mark.parametrize("q", [0, 2])
def test_tiles_in_memory(m, n, b, q):
    a = np.random.default_rng(1).normal(size=(m, n))
    rows, cols = -(-m // b), -(-n // b)
    got = X.run_local(L.plan_qr(rows, cols), X.split(a, b), m, n, b)
    r = np.triu(X.join_tiles(got, "A", rows, cols))[:n]
    assert np.allclose(K.positive(r), K.positive(np.linalg.qr(a)[1]))
    tiles = X.split(a, b) | X.split(np.eye(m), b, "U") | X.split(np.eye(n), b, "V")
    got = X.run_local(L.plan_utv(rows, cols, q, True), tiles, m, n, b)
    t, u, v = X.join_tiles(got, "A", rows, cols), X.join_tiles(got, "U", rows, rows), X.join_tiles(got, "V", cols, cols)
    assert np.allclose(u @ t @ v.T, a) and np.allclose(u.T @ u, np.eye(m)) and np.allclose(np.tril(t, -1), 0)


def test_waves_respect_dependences_and_spark_gives_the_same(spark):
    import pyspark.sql.functions as F

    tasks = L.plan_utv(2, 2)
    level = L.waves(tasks)
    for i, s in enumerate(tasks):
        for t, lt in zip(tasks[i + 1 :], level[i + 1 :]):
            if set(s.outs) & (set(t.ins) | set(t.outs)) or set(s.ins) & set(t.outs):
                assert lt > level[i]
    a = np.random.default_rng(2).normal(size=(7, 6))
    want = X.run_local(tasks, X.split(a, 4), 7, 6, 4)
    rows = [(k, v.shape[0], v.shape[1], bytearray(np.ascontiguousarray(v).tobytes())) for k, v in X.split(a, 4).items()]
    df = spark.createDataFrame(rows, X.STORE)
    for mode in ("direct", "overlap"):
        run = X.run_waves(tasks, df, 7, 6, 4, mode=mode)
        got = {r.name: np.frombuffer(r.data).reshape(r.nr, r.nc) for r in run.tiles("A").collect()}
        assert all(np.allclose(got[k], want[k]) for k in got) and len(got) == 4
        # just the tiles that tasks change are written, and each lane's times are kept
        assert run.written[0] == sum(len(t.outs) for t in tasks) and {x[0] for x in run.trace} == ({"compute", "read"} if mode == "overlap" else {"compute"})
        assert all(start <= end for _, _, start, end, _ in run.trace)
    # started again on the same folder, nothing is run anew
    again = X.run_waves(tasks, df, 7, 6, 4, mode="direct", root=run.root)
    assert again.trace == [] and again.manifest == run.manifest and again.tiles("A").count() == 4


@pytest.mark.parametrize("m,n,b", [(20, 8, 4), (13, 5, 4), (9, 9, 3), (30, 6, 3)])
def test_tree_over_tile_columns(m, n, b):
    a = np.random.default_rng(1).normal(size=(m, n))
    rows, cols = -(-m // b), -(-n // b)
    tasks = L.plan_qr(rows, cols, True)
    for workers in (1, 3):
        got = X.run_local(tasks, X.split(a, b), m, n, b, workers=workers)
        r = np.triu(X.join_tiles(got, "A", rows, cols))[:n]
        assert np.allclose(K.positive(r), K.positive(np.linalg.qr(a)[1]))
    chain, tree = (max(L.waves(L.plan_qr(64, 2, x))) for x in (False, True))
    assert tree < chain / 3


def test_utv_by_tiles_beside_each_other():
    from tilerank.operators import baselines

    a = np.random.default_rng(3).normal(size=(24, 20))
    u, t, v = baselines.utv_tiles(a, 8, 1, workers=4)
    assert np.allclose(u @ t @ v.T, a) and np.allclose(u.T @ u, np.eye(24)) and np.allclose(np.tril(t, -1), 0)
    assert len(baselines.utv_tiles(a, 8, 1, uv=False, workers=2)) == 1
    u, t, v = baselines.utv_dense(a, 8, 1, threads=1)
    assert np.allclose(u @ t @ v.T, a)
    with X.blas_threads(1) as known:
        assert known in (True, False)


def test_lanes_and_windows():
    tasks = L.plan_utv(3, 3)
    rows = L.lanes(tasks, [t.flops for t in tasks], [1.0] * len(tasks), 12, 2)
    assert max(x["end"] for x in rows) == L.schedule(tasks, [t.flops for t in tasks], [1.0] * len(tasks), 12, 2)
    for lane in {x["lane"] for x in rows}:
        mine = [x for x in rows if x["lane"] == lane]
        assert all(a["end"] <= b["start"] + 1e-9 for a, b in zip(mine, mine[1:]))
    early = L.window(rows, 1 / 6)
    assert 0 < len(early) < len(rows) / 2


def test_reuse_distances_equal_brute_force():
    tasks = L.plan_utv(3, 3, 1, True)
    touches = [x for t in tasks for x in [*t.ins, *t.outs]]
    got = L.reuse_distances(tasks)
    for i, x in enumerate(touches):
        before = max((j for j in range(i) if touches[j] == x), default=None)
        assert got[i]["dist"] == (-1 if before is None else len(set(touches[before + 1 : i])))


def test_cost_model():
    gib = 1 << 30
    assert (C.max_incore_n(48 * gib, 1), C.max_incore_n(48 * gib, 3)) == (80264, 46340)
    assert C.write_volume("right", 1000, 100) > 3 * C.write_volume("left", 1000, 100) == 3_000_000
    assert C.choose_regime(1e9, 1000, 100) == "triangle" and C.choose_regime(1e9, 100_000, 100) == "left" and C.choose_regime(1e7, 10**7, 1000) == "tiles"
    assert C.ratios(229627.6, 41312.9, 229910.0)["real_by_compute"] == pytest.approx(1.001, abs=1e-3)
