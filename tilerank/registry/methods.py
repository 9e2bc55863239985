"""Factorizations, baselines and measures on the carrier matrices."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilerank.functions import kernels as K
from tilerank.functions.keyed import gaussian_sql, gaussians
from tilerank.operators import apps, baselines, quality, reflect, sketchqr, utv
from tilerank.operators.matrix import Tall
from tilerank.sources import factors
from tilerank.sources import tables as T

from . import sqlgen as G

SEED = 7
QUERIES: dict = {}
ORACLES: dict = {}


def register(name: str, oracle: str | None = None):
    def put(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return put


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) + 0.0 for c in columns})


def frame(spark: SparkSession, rows: list, schema: str, *columns: str) -> DataFrame:
    """A small driver-side result; doubles rounded to 6 digits."""
    return rounded(spark.createDataFrame(rows, schema), *columns)


def pivot_frame(spark: SparkSession, f: sketchqr.PivotedQR, k: int | None = None) -> DataFrame:
    k = f.k if k is None else k
    rows = [(i, int(f.perm[i]), float(f.r[i, i])) for i in range(k)]
    return frame(spark, rows, "k bigint, pivot bigint, r_kk double", "r_kk")


def triangle_frame(spark: SparkSession, r: np.ndarray, scale: float = 1.0) -> DataFrame:
    rows = [(i, j, float(r[i, j] / scale)) for i in range(len(r)) for j in range(i, r.shape[1])]
    return frame(spark, rows, "i bigint, j bigint, r_ij double", "r_ij")


def entry_frame(rows: DataFrame) -> DataFrame:
    """Row frame -> (vec_id, col, v)."""
    return rounded(T.entries(rows).select(F.col("row_id").alias("vec_id"), F.col("col_id").cast("bigint").alias("col"), "v"), "v")


EMB_TABLE = f"SELECT CAST(row_id AS BIGINT) AS vec_id, CAST(col_id AS BIGINT) AS col, round(v, 6) + 0.0 AS v FROM ({G.EMB})"


def emb(spark: SparkSession, d: str) -> Tall:
    return Tall(T.emb(spark, d))


# classical and unpivoted

register("cpqr_emb_pivots", G.classical_pivots(G.EMB, 64))(lambda s, d: pivot_frame(s, sketchqr.pivoted_qr(emb(s, d))))
register("cpqr_line4_r", G.classical_pivots(G.LINE4, 4))(lambda s, d: pivot_frame(s, sketchqr.pivoted_qr(Tall(T.line4(s, d)))))
register("cpqr_userhour_r", G.classical_pivots(G.USERHOUR, 24))(lambda s, d: pivot_frame(s, sketchqr.pivoted_qr(Tall.stored(T.userhour(s, d)))))
register("cpqr_columnwise_emb", G.classical_pivots(G.EMB, 8))(lambda s, d: pivot_frame(s, sketchqr.pivoted_columnwise(emb(s, d), 8)))
DESIGN_RANK = G.rank(G.DESIGN, 12)
register("cpqr_design_rank", DESIGN_RANK)(lambda s, d: s.createDataFrame([(sketchqr.numerical_rank(sketchqr.pivoted_qr(Tall.stored(T.design(s, d))).r),)], "rank bigint"))
register("app_subset_emb", G.classical_pivots(G.EMB, 8))(lambda s, d: pivot_frame(s, sketchqr.pivoted_qr(emb(s, d), 8)))
register("leftqr_emb_r", G.fixed_r(G.EMB, 64))(lambda s, d: triangle_frame(s, sketchqr.left_qr(emb(s, d), 16)))
register("panelqr_emb_r", G.fixed_r(G.EMB, 64))(lambda s, d: triangle_frame(s, sketchqr.panel_qr(emb(s, d))))
register("qr_dense_emb_r", G.fixed_r(G.EMB, 64))(lambda s, d: triangle_frame(s, baselines.qr_dense(baselines.in_memory(emb(s, d)))))


@register("gram_pivoted_cholesky_emb", G.classical_pivots(G.EMB, 64))
def gram_pivoted(s: SparkSession, d: str) -> DataFrame:
    order, r = baselines.gram_pivoted_cholesky(emb(s, d))
    return frame(s, [(i, int(order[i]), float(r[i, i])) for i in range(len(r))], "k bigint, pivot bigint, r_kk double", "r_kk")


register("gram_cholesky_emb", G.fixed_r(G.EMB, 64))(lambda s, d: triangle_frame(s, baselines.gram_cholesky(emb(s, d))))
M_LINE = "(SELECT sqrt(sum(l_extendedprice * l_extendedprice)) FROM lineitem)"


@register("panelqr_line4_r", G.fixed_r(G.LINE4, 4, M_LINE))
def panelqr_line4(s: SparkSession, d: str) -> DataFrame:
    m = Tall(T.line4(s, d))
    return triangle_frame(s, sketchqr.panel_qr(m), float(m.column_norms()[1]))


@register("qr_append_rows", G.fixed_r(G.EMB, 64))
def qr_append_rows(s: SparkSession, d: str) -> DataFrame:
    rows = T.emb(s, d)
    return triangle_frame(s, sketchqr.append_rows(Tall(rows.where("row_id % 2 = 0")).triangle(), Tall(rows.where("row_id % 2 = 1"))))


# sketched

EMB_ROWS, USER_ROWS = "SELECT vec_id AS row_id FROM embeddings", "SELECT DISTINCT user_id AS row_id FROM events"
K16 = G.sketched_pivots(G.EMB, EMB_ROWS, 16, 8, SEED)
for name, schedule, sketch in (
    ("right", "right", ""), ("recompute", "left", "recompute"), ("pullback", "left", "pullback"), ("project", "left", "project"),
    ("upfront", "left", "upfront"), ("triangle", "triangle", ""),
):
    register(f"sketchqr_emb_k16_{name}", K16)(lambda s, d, a=schedule, b=sketch: pivot_frame(s, sketchqr.sketch_qr(emb(s, d), 8, 16, a, b, SEED)))
register("sketchqr_emb_k16_downdate", G.sketched_pivots(G.EMB, EMB_ROWS, 16, 8, SEED, True))(lambda s, d: pivot_frame(s, sketchqr.sketch_qr(emb(s, d), 8, 16, "left", "downdate", SEED)))
register("sketchqr_userhour_k8", G.sketched_pivots(G.USERHOUR, USER_ROWS, 8, 4, SEED))(lambda s, d: pivot_frame(s, sketchqr.sketch_qr(Tall.stored(T.userhour(s, d)), 4, 8, "left", "project", SEED)))
register(
    "sketch_emb_y",
    f"SELECT CAST(s AS BIGINT) AS s, CAST(col_id AS BIGINT) AS col, round(sum(v * {gaussian_sql(SEED, 'row_id', 's')}), 6) + 0.0 AS y FROM ({G.EMB}) CROSS JOIN (SELECT unnest(range(8)) AS s) GROUP BY 1, 2",
)(lambda s, d: frame(s, [(i, j, float(v)) for i, row in enumerate(emb(s, d).left(lambda ids: gaussians(SEED, ids, 8))) for j, v in enumerate(row)], "s bigint, col bigint, y double", "y"))
register("sketch_emb_block1_pivots", f"WITH {G.sketched(G.EMB, EMB_ROWS, 8, 8, SEED)} SELECT k, \"pivot\" FROM ({G.pivots(8)})")(
    lambda s, d: s.createDataFrame([(i, int(p)) for i, p in enumerate(K.pivoted(emb(s, d).left(lambda ids: gaussians(SEED, ids, 8)), 8)[0][:8])], "k bigint, pivot bigint")
)
FROB_EMB = f"SELECT round(sum(v * v), 6) + 0.0 AS energy FROM ({G.EMB})"
register("sketchqr_emb_energy", FROB_EMB)(lambda s, d: frame(s, [(float((sketchqr.sketch_qr(emb(s, d), 16, None, "left", "project", SEED).r ** 2).sum()),)], "energy double", "energy"))


# layouts: what is stored, and where its columns are


@register("sketchqr_emb_k16_virtual", G.sketched_rows(G.EMB, EMB_ROWS, 64, 16, 8, SEED, False))
def sketchqr_virtual(s: SparkSession, d: str) -> DataFrame:
    """R P': columns stay where they stand while the trailing matrix is rewritten."""
    f = sketchqr.sketch_qr(emb(s, d), 8, 16, "right", seed=SEED, layout="virtual")
    r = f.virtual()
    return frame(s, [(i, c, float(r[i, c])) for i in range(f.k) for c in range(64) if c not in f.perm[:i]], "i bigint, col bigint, r double", "r")


@register("sketchqr_emb_k16_physical", G.sketched_rows(G.EMB, EMB_ROWS, 64, 16, 8, SEED, True))
def sketchqr_physical(s: SparkSession, d: str) -> DataFrame:
    """R as stored: each step's write moved the columns into pivot order; read back from the factor table."""
    f = sketchqr.sketch_qr(emb(s, d), 8, 16, "right", seed=SEED, layout="physical")
    stored = factors.read_triangle(s, factors.save_factor(s, f))
    return rounded(stored.select("i", F.posexplode("r").alias("pos", "r")).where("pos >= i").select("i", F.col("pos").cast("bigint").alias("pos"), "r"), "r")


register("sketchqr_emb_residuals", G.sketched_residuals(G.EMB, EMB_ROWS, 16, 8, SEED))(
    lambda s, d: frame(s, [(8 * (x["step"] + 1), x["residual"]) for x in sketchqr.sketch_qr(emb(s, d), 8, 16, "left", "project", SEED).steps], "k bigint, residual double", "residual")
)


# orthogonal factors, formed as tables and multiplied with A: Q'Q is the identity, Q'A X equals the triangle


def identity_sql(k: int, n: int) -> str:
    grid = f"(SELECT unnest(range({k})) AS i), (SELECT unnest(range({{}})) AS j)"
    return (
        f"SELECT 'basis' AS part, i, j, CASE WHEN i = j THEN 1.0 ELSE 0.0 END AS v FROM {grid.format(k)} "
        f"UNION ALL SELECT 'triangle', i, j, 0.0 FROM {grid.format(n)}"
    )


def identities(s: SparkSession, q: DataFrame, mat: Tall, x: np.ndarray, t: np.ndarray) -> DataFrame:
    """Q'Q, and Q'A X less T, from the joined rows of Q and A."""
    k, n = len(t), mat.n
    both = q.select("row_id", F.col("x").alias("q")).join(mat.df, "row_id").select("row_id", F.concat("q", "x").alias("x"))
    g = Tall(both, k + n).reduce(lambda _, a: a[:, :k].T @ a)
    off = g[:, k:] @ x - t
    rows = [("basis", i, j, float(g[i, j])) for i in range(k) for j in range(k)]
    rows += [("triangle", i, j, float(off[i, j])) for i in range(k) for j in range(off.shape[1])]
    return frame(s, rows, "part string, i bigint, j bigint, v double", "v")


def moved(perm: list[int]) -> np.ndarray:
    return np.eye(len(perm))[:, perm]


@register("sketchqr_emb_identity", identity_sql(64, 64))
def sketchqr_identity(s: SparkSession, d: str) -> DataFrame:
    f = sketchqr.sketch_qr(emb(s, d), 16, None, "left", "project", SEED)
    return identities(s, f.q(), f.mat, moved(f.perm), f.r)


@register("sketchqr_emb_physical_identity", identity_sql(64, 64))
def physical_identity(s: SparkSession, d: str) -> DataFrame:
    f = sketchqr.sketch_qr(emb(s, d), 16, None, "right", seed=SEED, layout="physical")
    return identities(s, f.q(), f.mat, moved(f.perm), f.r)


@register("reflectorqr_emb_identity", identity_sql(64, 64))
def reflector_identity(s: SparkSession, d: str) -> DataFrame:
    """Stored reflectors, Q by back-accumulation, over sketched pivots."""
    perm = sketchqr.sketch_qr(emb(s, d), 16, None, "left", "project", SEED).perm
    f = reflect.reflector_qr(emb(s, d), 16, perm)
    return identities(s, f.q(), f.mat, moved(perm), f.r)


register("reflectorqr_emb_r", G.fixed_r(G.EMB, 64))(lambda s, d: triangle_frame(s, K.positive(reflect.reflector_qr(emb(s, d), 16).r)))


@register("reflectorqr_emb_vectors", "SELECT CAST(s AS BIGINT) AS step, count(*) AS n, CAST(0 AS BIGINT) AS above FROM embeddings, (SELECT unnest(range(4)) AS s) GROUP BY 1")
def reflector_vectors(s: SparkSession, d: str) -> DataFrame:
    """The reflectors as stored by step: how many rows, and entries above the unit diagonal that aren't zero."""
    f = reflect.reflector_qr(emb(s, d), 16)
    stored = factors.read_reflectors(s, factors.save_factor(s, f)).withColumnRenamed("step", "panel")
    place = F.get(F.map_values(F.map_filter(F.create_map(*[F.lit(int(x)) for kv in zip(f.run.top, range(64)) for x in kv]), lambda k, _: k == F.col("row_id"))), F.lit(0))
    own = F.when(place >= F.col("panel") * 16, place - F.col("panel") * 16)
    wrong = F.when(place < F.col("panel") * 16, F.size(F.filter("w", lambda x: F.abs(x) > 1e-12))).when(own < 16, F.size(F.filter("w", lambda x, i: ((i > own) & (F.abs(x) > 1e-12)) | ((i == own) & (F.abs(x - 1) > 1e-9))))).otherwise(0)
    return stored.groupBy(F.col("panel").cast("bigint").alias("step")).agg(F.count("*").alias("n"), F.sum(wrong).cast("bigint").alias("above"))


@register("sketchqr_userhour_partial", f"SELECT round(sqrt(sum(v * v)), 6) + 0.0 AS frob FROM ({G.USERHOUR})")
def userhour_partial(s: SparkSession, d: str) -> DataFrame:
    f = sketchqr.sketch_qr(Tall.stored(T.userhour(s, d)), 4, 8, "left", "pullback", SEED)
    return frame(s, [(float(np.sqrt(f.residual**2 + (f.r**2).sum())),)], "frob double", "frob")




@register("sketchqr_line4_full", f"SELECT CAST(count(*) AS BIGINT) AS columns, round(sum(e), 6) + 0.0 AS energy FROM (SELECT col_id, sum(v * v) / {M_LINE} / {M_LINE} AS e FROM ({G.LINE4}) GROUP BY 1)")
def sketchqr_line4_full(s: SparkSession, d: str) -> DataFrame:
    """All columns, ragged last block: the triangle keeps the energy."""
    m = Tall(T.line4(s, d))
    f = sketchqr.sketch_qr(m, 3, None, "left", "project", SEED, rng="mix")
    return frame(s, [(f.k, float((f.r**2).sum() / m.column_norms()[1] ** 2))], "columns bigint, energy double", "energy")


# UTV

def utv_identity(s: SparkSession, f: utv.UTV) -> DataFrame:
    return identities(s, f.u(), f.mat, f.v, f.t[: f.k])


for q in (0, 1, 2):
    register(f"utv_q{q}_emb_energy", FROB_EMB)(lambda s, d, q=q: frame(s, [(float((utv.power_utv(emb(s, d), 16, q, None, "left", SEED).t ** 2).sum()),)], "energy double", "energy"))
    register(f"utv_q{q}_emb_identity", identity_sql(64, 64))(lambda s, d, q=q: utv_identity(s, utv.power_utv(emb(s, d), 16, q, None, "right", SEED)))


def logvol(s: SparkSession, d: str, q: int) -> DataFrame:
    t = utv.power_utv(emb(s, d), 4, q, 4, "left", SEED).diagonal()[:4]
    return frame(s, [(float(np.log(t).sum()),)], "logvol double", "logvol")


def logvol_sql(q: int, b: int = 4) -> str:
    """With Y = (A'A)^q A'G: half of ln det(Y'A'AY) - ln det(Y'Y), both by elimination."""
    parts = [f"e AS MATERIALIZED ({G.EMB})", "h AS MATERIALIZED (SELECT a.col_id AS i, b.col_id AS j, sum(a.v * b.v) AS v FROM e a JOIN e b USING (row_id) GROUP BY 1, 2)"]
    parts.append(f"x0 AS MATERIALIZED (SELECT col_id AS i, s AS j, sum(v * {gaussian_sql(SEED, 'row_id', 's')}) AS v FROM e CROSS JOIN (SELECT unnest(range({b})) AS s) GROUP BY 1, 2)")
    for t in range(q + 1):
        parts.append(f"x{t + 1} AS MATERIALIZED (SELECT h.i, x.j, sum(h.v * x.v) AS v FROM h JOIN x{t} x ON h.j = x.i GROUP BY 1, 2)")
    out = []
    for name, left, right in (("n", f"x{q}", f"x{q + 1}"), ("d", f"x{q}", f"x{q}")):
        parts.append(f"{name}0 AS MATERIALIZED (SELECT a.j AS i, b.j AS j, sum(a.v * b.v) AS v FROM {left} a JOIN {right} b ON a.i = b.i GROUP BY 1, 2)")
        for t in range(b):
            parts.append(f"{name}p{t} AS MATERIALIZED (SELECT i AS p, v AS d FROM {name}{t} WHERE i = {t} AND j = {t})")
            if t + 1 < b:
                parts.append(f"{name}{t + 1} AS MATERIALIZED ({G.eliminated(f'{name}{t}', f'{name}p{t}')})")
        out.append(" + ".join(f"(SELECT ln(d) FROM {name}p{t})" for t in range(b)))
    return f"WITH {', '.join(parts)} SELECT round(0.5 * (({out[0]}) - ({out[1]})), 6) + 0.0 AS logvol"


for q in (0, 1, 2):
    register(f"utv_q{q}_emb_tile0_logvol", logvol_sql(q))(lambda s, d, q=q: logvol(s, d, q))


@register("utv_emb_orthogonality", "SELECT i, j, CASE WHEN i = j THEN 1.0 ELSE 0.0 END AS v FROM (SELECT unnest(range(64)) AS i) CROSS JOIN (SELECT unnest(range(64)) AS j)")
def utv_orthogonality(s: SparkSession, d: str) -> DataFrame:
    v = utv.power_utv(emb(s, d), 16, 1, None, "left", SEED).v
    g = v.T @ v
    return frame(s, [(i, j, float(g[i, j])) for i in range(64) for j in range(64)], "i bigint, j bigint, v double", "v")


@register("utv_emb_lower_mass", "SELECT CAST(unnest(range(4)) AS BIGINT) AS step, CAST(0 AS BIGINT) AS nonzeros")
def utv_lower_mass(s: SparkSession, d: str) -> DataFrame:
    """Entries under the diagonal of U'A V, by step, from U as a table."""
    f = utv.power_utv(emb(s, d), 16, 1, None, "left", SEED)
    both = f.u().select("row_id", F.col("x").alias("u")).join(f.mat.df, "row_id").select("row_id", F.concat("u", "x").alias("x"))
    t = Tall(both, 128).reduce(lambda _, a: a[:, :64].T @ a[:, 64:]) @ f.v
    low = np.abs(np.tril(t, -1)) > 1e-8 * np.abs(t).max()
    return s.createDataFrame([(i, int(np.count_nonzero(low[:, 16 * i : 16 * i + 16]))) for i in range(4)], "step bigint, nonzeros bigint")


for schedule in ("left", "triangle"):
    register(f"utv_{schedule}_emb_identity", identity_sql(64, 64))(lambda s, d, x=schedule: utv_identity(s, utv.power_utv(emb(s, d), 16, 1, None, x, SEED)))
USER_GRAM = f"WITH e AS ({G.USERHOUR}), f AS (SELECT sum(v * v) AS f FROM e) SELECT CAST(a.col_id AS BIGINT) AS i, CAST(b.col_id AS BIGINT) AS j, round(sum(a.v * b.v) / any_value(f), 6) + 0.0 AS v FROM e a JOIN e b USING (row_id) CROSS JOIN f GROUP BY 1, 2"


@register("utv_userhour_gram_recon", USER_GRAM)
def utv_gram_recon(s: SparkSession, d: str) -> DataFrame:
    f = utv.power_utv(Tall.stored(T.userhour(s, d)), 4, 1, None, "left", SEED)
    g = f.v @ f.t.T @ f.t @ f.v.T
    g = g / np.trace(g)
    return frame(s, [(i, j, float(g[i, j])) for i in range(24) for j in range(24)], "i bigint, j bigint, v double", "v")


register("utv_design_rank", DESIGN_RANK)(lambda s, d: s.createDataFrame([(utv.power_utv(Tall.stored(T.design(s, d)), 4, 1, None, "left", SEED, tol=1e-8).rank(),)], "rank bigint"))
register("utv_gram_det", f"WITH {G.classical(G.EMB, 64)} SELECT round({' + '.join(f'(SELECT ln(d) FROM p{t})' for t in range(64))}, 6) + 0.0 AS logdet")(
    lambda s, d: frame(s, [(float(np.log(np.abs(np.diag(baselines.utv_dense(emb(s, d).gram(), 16, 1, SEED)[1]))).sum()),)], "logdet double", "logdet")
)

# baselines and measures

TRACES = """WITH e AS ({e}), h AS (SELECT a.col_id AS i, b.col_id AS j, sum(a.v * b.v) AS v FROM e a JOIN e b USING (row_id) GROUP BY 1, 2),
h2 AS (SELECT a.i, b.j, sum(a.v * b.v) AS v FROM h a JOIN h b ON a.j = b.i GROUP BY 1, 2), t AS (SELECT sum(v) AS f FROM h WHERE i = j)
SELECT CAST(1 AS BIGINT) AS p, round((SELECT sum(v) FROM h WHERE i = j) / power(f, 1 * {on}), 6) + 0.0 AS value FROM t
UNION ALL SELECT CAST(2 AS BIGINT), round((SELECT sum(v * v) FROM h) / power(f, 2 * {on}), 6) + 0.0 FROM t
UNION ALL SELECT CAST(3 AS BIGINT), round((SELECT sum(a.v * b.v) FROM h2 a JOIN h b ON a.i = b.i AND a.j = b.j) / power(f, 3 * {on}), 6) + 0.0 FROM t"""


def power_sums(s: SparkSession, m: Tall, scaled: bool) -> DataFrame:
    sv = baselines.svd_dense(m, False)[1]
    f = float((sv**2).sum()) if scaled else 1.0
    return frame(s, [(p, float((sv ** (2 * p)).sum() / f**p)) for p in (1, 2, 3)], "p bigint, value double", "value")


register("svd_emb_power_sums", TRACES.format(e=G.EMB, on=1))(lambda s, d: power_sums(s, emb(s, d), True))
register("svd_tall_line4_power_sums", TRACES.format(e=G.LINE4, on=1))(lambda s, d: power_sums(s, Tall(T.line4(s, d)), True))
register("lin_trace_powers", TRACES.format(e=G.EMB, on=0).replace("round((", "round(0.001 * ("))(
    lambda s, d: frame(s, [(p, float(0.001 * np.trace(np.linalg.matrix_power(emb(s, d).gram(), p)))) for p in (1, 2, 3)], "p bigint, value double", "value")
)
register("err_rank_k_emb")(lambda s, d: frame(s, quality.rank_k_errors(emb(s, d), [8, 16, 32, 48], 8, SEED), "method string, k bigint, q bigint, ratio double, ratio_frob double", "ratio", "ratio_frob"))
register("err_rank_k_userhour")(lambda s, d: frame(s, quality.rank_k_errors(Tall.stored(T.userhour(s, d)), [1, 4, 8, 16], 4, SEED), "method string, k bigint, q bigint, ratio double, ratio_frob double", "ratio", "ratio_frob"))
register("err_diag_vs_sv")(lambda s, d: frame(s, quality.diag_deviation(emb(s, d), 8, SEED), "q bigint, max_dev double, mean_dev double", "max_dev", "mean_dev"))
VOLUMES = " UNION ALL ".join([
    G.half_log_volume("classical", G.classical(G.EMB, 16), 16), G.half_log_volume("sketched", G.sketched(G.EMB, EMB_ROWS, 16, 8, SEED), 16),
    G.half_log_volume("downdated", G.sketched(G.EMB, EMB_ROWS, 16, 8, SEED, True), 16),
])
register("err_pivot_volume", VOLUMES)(lambda s, d: frame(s, quality.pivot_volumes(emb(s, d), 16, 8, SEED), "method string, log_volume double", "log_volume"))
register("err_subspace_gap")(lambda s, d: frame(s, quality.subspace_gaps(emb(s, d), 8, SEED), "q bigint, sine double", "sine"))
register("err_invariants")(lambda s, d: s.createDataFrame(quality.invariants(emb(s, d), 16, SEED), "method string, residual double, orthogonality double, lower_mass double"))
register("base_spark_linalg")(lambda s, d: frame(s, baselines.spark_linalg(T.emb(s, d)), "method string, k bigint, value double", "value"))

@register("app_lstsq_line4")
def app_lstsq(s: SparkSession, d: str) -> DataFrame:
    li = T.load(s, d, "lineitem")
    x = Tall(T.rows_from_columns(li, T.line_key(), [F.lit(1.0), F.col("l_quantity"), F.col("l_discount") * 100, F.col("l_tax") * 100, F.col("l_extendedprice") / 1000]))
    coef, residual = apps.lstsq(x, 4)
    return frame(s, [(i, float(c)) for i, c in enumerate(coef)], "j bigint, coef double", "coef")


def lstsq_sql() -> str:
    cols = ["1.0", "l_quantity", "l_discount * 100", "l_tax * 100", "l_extendedprice / 1000"]
    parts = [G.gram(G.unpivot(cols, "lineitem"))]
    for t in range(4):
        parts.append(f"p{t} AS MATERIALIZED (SELECT i AS p, v AS d FROM g{t} WHERE i = {t} AND j = {t})")
        parts.append(f"r{t} AS MATERIALIZED (SELECT g.j, g.v / p.d AS v FROM g{t} g, p{t} p WHERE g.i = {t})")
        parts.append(f"g{t + 1} AS MATERIALIZED ({G.eliminated(f'g{t}', f'p{t}')})")
    for t in (3, 2, 1, 0):
        rest = "".join(f" - (SELECT v FROM r{t} WHERE j = {u}) * (SELECT x FROM x{u})" for u in range(t + 1, 4))
        parts.append(f"x{t} AS MATERIALIZED (SELECT (SELECT v FROM r{t} WHERE j = 4){rest} AS x)")
    return f"WITH {', '.join(parts)} {' UNION ALL '.join(f'SELECT CAST({t} AS BIGINT) AS j, round(x, 6) + 0.0 AS coef FROM x{t}' for t in range(4))}"


ORACLES["app_lstsq_line4"] = lstsq_sql()
TRI = lstsq_sql()


@register("lin_tri_solve", TRI)
def lin_tri_solve(s: SparkSession, d: str) -> DataFrame:
    """The same coefficients by back substitution on the triangle of [X | y]."""
    li = T.load(s, d, "lineitem")
    x = Tall(T.rows_from_columns(li, T.line_key(), [F.lit(1.0), F.col("l_quantity"), F.col("l_discount") * 100, F.col("l_tax") * 100, F.col("l_extendedprice") / 1000]))
    r = x.triangle()
    coef = K.solve_upper(r[:4, :4], r[:4, 4:])[:, 0]
    return frame(s, [(i, float(c)) for i, c in enumerate(coef)], "j bigint, coef double", "coef")


register("app_tls_line4")(lambda s, d: frame(s, [(i, float(c)) for i, c in enumerate(apps.tls(Tall(T.line4(s, d)), 3))], "j bigint, coef double", "coef"))


@register("reflectorqr_emb_apply", G.fixed_r(G.EMB, 64))
def reflector_apply(s: SparkSession, d: str) -> DataFrame:
    """Q'A by the reflectors is the triangle."""
    f = reflect.reflector_qr(emb(s, d), 16)
    return triangle_frame(s, K.positive(np.triu(reflect.apply_qt(f, f.mat.df, 64))))


@register("app_rank_k_project")
def app_rank_k_project(s: SparkSession, d: str) -> DataFrame:
    m = Tall.stored(apps.term_rows(T.load(s, d, "documents"), 256), 256)
    return frame(s, apps.kept_energy(m, [8, 16, 32], SEED), "k bigint, kept double", "kept")
