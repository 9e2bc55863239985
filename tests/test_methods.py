import numpy as np
import pytest

from tilerank.functions import kernels as K
from tilerank.operators import sketchqr as S
from tilerank.operators import utv as U
from tilerank.operators.matrix import Tall, with_index
from tilerank.sources import tables


@pytest.fixture(scope="module")
def emb(spark, sf):
    return tables.emb(spark, sf).repartition(3, "row_id").cache()


@pytest.fixture(scope="module")
def a(emb):
    return np.array([r.x for r in emb.orderBy("row_id").collect()])


def dense(df):
    return np.array([r.x for r in df.orderBy("row_id").collect()])


def test_triangle_and_products(emb, a):
    m = Tall(emb)
    assert np.allclose(m.triangle(), K.positive(np.linalg.qr(a)[1])) and np.allclose(m.gram(), a.T @ a)
    assert np.isclose(m.frob(), np.linalg.norm(a)) and np.allclose(m.column_norms(), np.linalg.norm(a, axis=0)) and m.passes == 4
    assert np.allclose(dense(m.times(np.eye(64)[:, :3])), a[:, :3])
    assert np.allclose(m.reduce(lambda _, x: K.r_only(x), K.r_only, fan_in=2) ** 2, np.linalg.qr(a)[1] ** 2)


def test_passes_and_flops_are_as_the_cost_model_says(emb):
    from tilerank.plans import costmodel as C

    for schedule, sketch in [("left", x) for x in ("recompute", "pullback", "project", "upfront", "downdate")] + [("right", ""), ("triangle", "")]:
        f = S.sketch_qr(Tall(emb), 8, 24, schedule, sketch)
        assert f.passes == C.passes(schedule, sketch, 24, 8), (schedule, sketch, f.passes)
    # a partial run's work is linear in k as long as k is well under n, and a full triangle's is not needed for it
    assert C.tall_flops(10**6, 1000, 50, 10) < 2.1 * C.tall_flops(10**6, 1000, 25, 5) < C.tall_flops(10**6, 1000, 1000, 10) / 8


class Counted(Tall):
    """Adds up the sizes of the arrays that passes gather."""

    gathered = 0

    def reduce(self, *a, **b):
        got = super().reduce(*a, **b)
        self.gathered = max(self.gathered, got.size)
        return got


def test_a_partial_run_gathers_thin_arrays_only(emb):
    mat = Counted(emb)
    S.sketch_qr(mat, 4, 16, "left", "project")
    assert mat.gathered <= 3 * 4 * 64


VARIANTS = [("left", s) for s in ("recompute", "pullback", "project", "upfront")] + [("right", ""), ("triangle", "")]


def test_all_schedules_choose_the_same_pivots(emb, a):
    found = {v: S.sketch_qr(Tall(emb), 8, 16, *v) for v in VARIANTS}
    base = found["left", "pullback"]
    for v, f in found.items():
        assert f.perm == base.perm and np.allclose(f.r, base.r, atol=1e-9), v
        assert np.isclose(f.residual**2 + (f.r**2).sum(), (a * a).sum())
    assert found["right", ""].written == 1 and base.written == 0 and found["triangle", ""].passes == 1
    assert [round(x["residual"], 9) for x in base.steps] == [round(x["residual"], 9) for x in found["right", ""].steps]
    down = S.sketch_qr(Tall(emb), 8, 16, "left", "downdate")
    assert down.perm[:8] == base.perm[:8] and down.k == 16
    q = dense(base.q())
    assert np.allclose(q.T @ q, np.eye(16)) and np.allclose(q @ base.virtual(), dense(base.reconstruct()))
    assert np.allclose(dense(base.physical())[:, :16], a[:, base.perm[:16]])
    best = np.linalg.svd(a, compute_uv=False)[16]
    assert np.linalg.norm(a - q @ base.virtual(), 2) < 2 * best


def test_layouts_and_the_residual_as_stopping_rule(emb, a):
    base = S.sketch_qr(Tall(emb), 8, 24, "left", "project")
    for layout in ("virtual", "physical"):
        f = S.sketch_qr(Tall(emb), 8, 24, "right", layout=layout)
        assert f.perm == base.perm and np.allclose(f.r, base.r, atol=1e-9) and f.written == 2
    with pytest.raises(ValueError):
        S.sketch_qr(Tall(emb), 8, 24, "right", layout="sideways")
    norm = np.linalg.norm(a)
    for schedule, sketch in VARIANTS:
        f = S.sketch_qr(Tall(emb), 8, None, schedule, sketch, error=0.6)
        assert f.residual <= 0.6 * norm < f.steps[-2]["residual"] and f.k % 8 == 0, (schedule, sketch)
        q = np.linalg.qr(a[:, f.perm[: f.k]])[0]
        assert np.isclose(f.residual, np.linalg.norm(a - q @ (q.T @ a)))


@pytest.mark.parametrize("kind", ["power", "decay", "plain"])
def test_reflectors_stay_orthogonal(spark, kind):
    from tilerank.operators import reflect

    rng = np.random.default_rng(5)
    m, n = 300, 24
    x = np.linspace(0.1, 1, m)
    a = {
        "power": x[:, None] ** np.arange(n)[None, :],
        "decay": np.linalg.qr(rng.normal(size=(m, n)))[0] * 10.0 ** (-0.5 * np.arange(n))[None, :] @ np.linalg.qr(rng.normal(size=(n, n)))[0],
        "plain": rng.normal(size=(m, n)),
    }[kind]
    df = spark.createDataFrame([(7 * i - 40, r.tolist()) for i, r in enumerate(a)], "row_id long, x array<double>").repartition(3)
    for b in (5, 24):
        f = reflect.reflector_qr(Tall(df), b)
        q = dense(f.q())
        assert np.linalg.norm(q.T @ q - np.eye(n)) < 1e-12 and np.linalg.norm(q @ f.r - a) < 1e-13 * np.linalg.norm(a) * n
        assert np.allclose(np.tril(f.r, -1), 0)
    thin = np.linalg.solve(K.positive(np.linalg.qr(a)[1]).T, a.T).T
    assert kind == "plain" or np.linalg.norm(thin.T @ thin - np.eye(n)) > 1e-8
    w = {(r.step, r.row_id): r.w for r in reflect.reflector_qr(Tall(df), 5).reflectors().collect()}
    assert len(w) == 5 * m and w[1, -40] == [0.0] * 5 and len(w[4, -40]) == 4
    with pytest.raises(ValueError):
        reflect.reflector_qr(Tall(df.where("row_id < 0")), 5)


def test_factors_are_saved_and_loaded(spark, emb):
    from tilerank.operators import reflect
    from tilerank.sources import factors

    f = S.sketch_qr(Tall(emb), 8, 16, "left", "project")
    g = factors.load_factor(spark, factors.save_factor(spark, f), Tall(emb))
    assert g.perm == f.perm and np.array_equal(g.r, f.r) and g.residual == f.residual and g.q().count() == f.q().count()
    u = U.power_utv(Tall(emb), 16, 1, 16, "triangle")
    v = factors.load_factor(spark, factors.save_factor(spark, u), Tall(emb))
    assert np.array_equal(v.v, u.v) and np.array_equal(v.t, u.t)
    path = factors.save_factor(spark, reflect.reflector_qr(Tall(emb), 16, f.perm[:32]))
    assert factors.read_reflectors(spark, path, 1).count() == emb.count() == factors.read_reflectors(spark, path).count() / 2


def test_factorize_picks_a_schedule(spark, emb):
    from tilerank.operators.router import factorize

    emb.createOrReplaceTempView("some_rows__")
    assert factorize(spark, "SELECT row_id, x FROM some_rows__", "sketch_qr", k=16, b=8, rng="md5").perm == S.sketch_qr(Tall(emb), 8, 16, "triangle").perm
    assert factorize(spark, "SELECT row_id, x[0] AS p, x[1] AS q FROM some_rows__", "qr").r.shape == (2, 2)
    assert factorize(spark, "SELECT row_id, x FROM some_rows__", "utv", b=16).k == 64
    for bad in ("SELECT row_id, 'a' AS x FROM some_rows__", "SELECT row_id FROM some_rows__"):
        with pytest.raises(ValueError):
            factorize(spark, bad)


def test_full_ragged_and_deficient(spark, sf, emb, a):
    full = S.sketch_qr(Tall(emb), 24, None, "left", "project")
    assert sorted(full.perm) == list(range(64)) and full.residual < 1e-9 and np.allclose(dense(full.reconstruct()), a)
    design = tables.design(spark, sf)
    for v in VARIANTS:
        assert S.sketch_qr(Tall(design), 4, None, *v, tol=1e-8).k == 9, v
    assert S.numerical_rank(S.pivoted_qr(Tall(design)).r) == 9
    for schedule in ("left", "right", "triangle"):
        assert U.power_utv(Tall(design), 4, 1, None, schedule, tol=1e-8).rank() == 9, schedule


def test_classical_and_unpivoted(emb, a):
    whole = S.pivoted_qr(Tall(emb))
    assert whole.perm == K.pivoted(a)[0]
    assert S.pivoted_columnwise(Tall(emb), 5).perm[:5] == whole.perm[:5]
    r = K.positive(np.linalg.qr(a)[1])
    assert np.allclose(S.left_qr(Tall(emb), 20), r)
    half = emb.where("row_id % 2 = 0"), emb.where("row_id % 2 = 1")
    assert np.allclose(S.append_rows(Tall(half[0]).triangle(), Tall(half[1])), r)


@pytest.mark.parametrize("q", [0, 1])
def test_utv_schedules(emb, a, q):
    sv = np.linalg.svd(a, compute_uv=False)
    found = {s: U.power_utv(Tall(emb), 16, q, None, s) for s in ("left", "right", "triangle")}
    for s, f in found.items():
        assert np.allclose(dense(f.reconstruct()), a) and np.allclose(f.v.T @ f.v, np.eye(64)), s
        assert np.allclose(np.tril(f.t, -1), 0) and np.isclose((f.t**2).sum(), (a * a).sum()), s
        u = dense(f.u())
        assert np.allclose(u.T @ u, np.eye(64)), s
        assert np.allclose(f.diagonal(), found["left"].diagonal(), atol=1e-7), s
        assert abs(f.diagonal() - sv).max() < 0.3 * sv[0]
    part = U.power_utv(Tall(emb), 16, q, 16, "left")
    assert np.allclose(part.diagonal(), found["left"].diagonal()[:16])
    assert np.linalg.norm(a - dense(part.reconstruct()), 2) < 1.6 * sv[16]


def test_defined_cases(spark):
    bad = spark.createDataFrame([(1, [1.0, float("nan")])], "row_id long, x array<double>")
    with pytest.raises(Exception, match="NaN"):
        Tall(bad).gram()
    with pytest.raises(ValueError, match="empty"):
        Tall(bad.limit(0))
    one = Tall(spark.createDataFrame([(1, [3.0]), (2, [4.0])], "row_id long, x array<double>"))
    assert np.allclose(S.sketch_qr(one, 5).r, [[5.0]]) and U.power_utv(one, 9, 0).diagonal()[0] == pytest.approx(5)
    with pytest.raises(ValueError):
        U.power_utv(one, 1, -1)


def test_with_index(spark):
    df = spark.range(0, 1000, 7).selectExpr("id * 3 as row_id").repartition(5)
    assert [r.idx for r in with_index(df).orderBy("row_id").collect()] == list(range(143))


def test_accuracy_bands(emb):
    from tilerank.operators import quality as Q

    rows = {(m, k, q): r for m, k, q, r, _ in Q.rank_k_errors(Tall(emb), [8, 16, 32], 8, 7)}
    for k in (8, 16, 32):
        assert all(rows[x, k, 0] >= 1 - 1e-10 for x in ("classical", "sketched", "utv"))
        assert rows["sketched", k, 0] <= 2 * rows["classical", k, 0] and rows["utv", k, 2] <= rows["utv", k, 0] * 1.05
    dev = [d for _, d, _ in Q.diag_deviation(Tall(emb), 8, 7)]
    assert dev[2] < dev[1] < dev[0] < 0.4
    volumes = dict(Q.pivot_volumes(Tall(emb), 16, 8, 7))
    assert volumes["classical"] - volumes["sketched"] < 2
    assert all(res < 1e-12 and orth < 1e-10 and low == 0 for _, res, orth, low in Q.invariants(Tall(emb), 16, 7))


def test_run_report(spark, sf):
    from tilerank.plans.report import as_row, run_report

    rows = tables.emb(spark, sf).repartition(3)
    f, report = run_report(spark, lambda: S.sketch_qr(Tall(rows, 64), 8, 16, "right"))
    assert report.passes == f.passes and report.written == 1 and report.stages >= f.passes and report.tasks >= report.stages
    assert report.bytes_read > 0 < report.shuffle_written and as_row(report)["seconds"] > 0
    _, nothing = run_report(spark, lambda: None)
    assert nothing.stages == 0 and nothing.passes is None


def test_frame_operators(spark, emb, a):
    from tilerank.operators import reflect
    from tilerank.operators.matrix import equal_within, identity_rows, stack

    eye = identity_rows(spark, 64)
    assert np.array_equal(dense(eye), np.eye(64)) and np.isclose(Tall(emb).spectral_norm(), np.linalg.norm(a, 2))
    assert np.allclose(dense(stack(emb, eye)), np.vstack([a, np.eye(64)]))
    assert equal_within(emb, emb, 0.0) and not equal_within(emb, Tall(emb).map_rows(lambda _, x: x + 1e-3), 1e-4) and not equal_within(emb, eye, 1e9)
    f = reflect.reflector_qr(Tall(emb), 16)
    assert equal_within(reflect.apply_q(f, f.r), emb, 1e-10) and np.allclose(reflect.apply_qt(f, emb, 64), f.r)
    assert np.allclose(Tall.stored(emb.groupBy("row_id").agg({"x": "max"}).toDF("row_id", "x")).triangle(), Tall(emb).triangle())


def test_near_pairs_are_those_of_all_products_without_a_join_of_cells(spark):
    from tilerank.operators import apps

    rng = np.random.default_rng(5)
    a = np.repeat(rng.random((60, 8)), 4, axis=0) + 0.12 * rng.random((240, 8))
    a = np.vstack([a, a[:3], np.zeros((1, 8))])
    rows = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(a)], "row_id bigint, x array<double>")
    u = a[:240] / np.linalg.norm(a[:240], axis=1)[:, None]
    want = {(i, j) for i, j in zip(*np.nonzero(np.triu(u @ u.T >= 0.99, 1)))}
    pairs = apps.near_pairs(rows, 8, 0.99, 4, 2)
    assert {(r.a, r.b) for r in pairs.collect()} == want and pairs.count() == len(want)
    plan = pairs._jdf.queryExecution().analyzed().toString()
    assert "Generate explode" not in plan  # cells are not joined row by row


def test_term_rows_count_words_without_exploding_them(spark):
    from tilerank.operators import apps

    rows = [(1, "b A  a\t"), (2, None), (2, "a"), (3, ""), (4, "b a A ")]
    terms = apps.term_rows(spark.createDataFrame(rows, "doc_id bigint, text string"), 16)
    place = {w: int(__import__("hashlib").md5(w.encode()).hexdigest()[:8], 16) % 16 for w in ("a", "b", "")}
    want = {}
    for i, t in rows:
        for w in __import__("re").split("\\s+", (t or "").lower()):
            want.setdefault(i, np.zeros(16))[place[w]] += 1
    assert all(np.allclose(r.x, np.log1p(want[r.row_id])) for r in terms.collect()) and terms.count() == 4
    assert {(r.row_id, r.first_id) for r in apps.term_classes(terms).collect()} == {(1, 1), (2, 2), (3, 3), (4, 1)}
    assert "Generate" not in terms._jdf.queryExecution().executedPlan().toString()


def test_thin_products_shuffle_no_products(spark):
    from tilerank.operators import tiles as X

    rng = np.random.default_rng(6)
    a, b = rng.integers(-3, 4, (70, 10)).astype(float), rng.integers(-3, 4, (10, 45)).astype(float)
    a[16:32, :4] = 0.0
    p, q = (tables.to_tiles(spark.createDataFrame([(int(i), int(j), float(m[i, j])) for i, j in zip(*np.nonzero(m))], "row_id bigint, col_id int, v double"), 4, m.shape[1], m.shape[0]) for m in (a, b))
    made = X.multiply_thin(p, q, 18, 12, side=5)
    got = np.zeros((70, 45))
    for r in tables.from_tiles(made, 4).collect():
        got[r.row_id, r.col_id] += r.v
    assert np.array_equal(got, a @ b) and made.groupBy("bi", "bj").count().where("count > 1").isEmpty()
    from __spark_entry__ import queries

    plan = queries()["lin_tile_matmul"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapCoGroupsInArrow" in plan and "SortMergeJoin" not in plan and "BroadcastHashJoin" not in plan
