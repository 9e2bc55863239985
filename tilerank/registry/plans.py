"""Ledgers, replays, cost model, tile runs and simulated experiments."""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tilerank.functions import kernels as K
from tilerank.operators import tiles as X
from tilerank.operators.matrix import Tall, with_index
from tilerank.plans import costmodel as C
from tilerank.plans import ledger as L
from tilerank.sources import tables as T

from . import sqlgen as G
from .methods import rounded, triangle_frame

QUERIES: dict = {}
ORACLES: dict = {}


def register(name: str, oracle: str | None = None):
    def put(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return put


# The worked example's tasks as operation, in-blocks, out-blocks.
TWO_BY_TWO = [
    ("draw", "", "G_0"), ("draw", "", "G_1"),
    ("gemm_tn_set", "A_0_0,G_0", "Y_0"), ("gemm_tn_set", "A_0_1,G_0", "Y_1"),
    ("gemm_tn_add", "A_1_0,G_1,Y_0", "Y_0"), ("gemm_tn_add", "A_1_1,G_1,Y_1", "Y_1"),
    ("qr_dense", "Y_0", "Y_0,B_0"), ("qr_stacked", "Y_0,Y_1", "Y_0,Y_1,B_1"),
    ("right_dense", "Y_0,B_0,A_0_0", "A_0_0"), ("right_dense", "Y_0,B_0,A_1_0", "A_1_0"),
    ("right_stacked", "Y_1,B_1,A_0_0,A_0_1", "A_0_0,A_0_1"), ("right_stacked", "Y_1,B_1,A_1_0,A_1_1", "A_1_0,A_1_1"),
    ("qr_dense", "A_0_0", "A_0_0,C_0"), ("qr_stacked", "A_0_0,A_1_0", "A_0_0,A_1_0,C_1"),
    ("left_dense", "A_0_0,C_0,A_0_1", "A_0_1"), ("left_stacked", "A_1_0,C_1,A_0_1,A_1_1", "A_0_1,A_1_1"),
    ("keep_upper", "A_0_0", "A_0_0"), ("set_zero", "", "A_1_0"),
    ("svd", "A_0_0", "A_0_0,P_0,Q_0"), ("times_left", "P_0,A_0_1", "A_0_1"),
    ("svd", "A_1_1", "A_1_1,P_0,Q_0"), ("times_right", "A_0_1,Q_0", "A_0_1"),
]
VALUES = ", ".join(f"(CAST({i} AS INTEGER), '{op}', '{a}', '{b}')" for i, (op, a, b) in enumerate(TWO_BY_TWO))
TASKS = f"tasks(seq, op, ins, outs) AS (VALUES {VALUES})"
COUNT = "CASE WHEN {0} = '' THEN 0 ELSE len(string_split({0}, ',')) END"


# The same for a grid of one tile row.
ONE_BY_TWO = [
    ("draw", "", "G_0"), ("gemm_tn_set", "A_0_0,G_0", "Y_0"), ("gemm_tn_set", "A_0_1,G_0", "Y_1"),
    ("qr_dense", "Y_0", "Y_0,B_0"), ("qr_stacked", "Y_0,Y_1", "Y_0,Y_1,B_1"),
    ("right_dense", "Y_0,B_0,A_0_0", "A_0_0"), ("right_stacked", "Y_1,B_1,A_0_0,A_0_1", "A_0_0,A_0_1"),
    ("qr_dense", "A_0_0", "A_0_0,C_0"), ("left_dense", "A_0_0,C_0,A_0_1", "A_0_1"), ("keep_upper", "A_0_0", "A_0_0"),
    ("svd", "A_0_0", "A_0_0,P_0,Q_0"), ("times_left", "P_0,A_0_1", "A_0_1"),
]
ONE_VALUES = ", ".join(f"(CAST({i} AS INTEGER), '{op}', '{a}', '{b}')" for i, (op, a, b) in enumerate(ONE_BY_TWO))
# Each user's events are a matrix of 64 columns, cut into panels of 64 rows: grids of one or two tile rows of 32, and two tile columns.
PANELS = """panels AS (SELECT user_id, CAST(k AS BIGINT) AS panel, CASE WHEN n - 64 * k > 32 THEN 2 ELSE 1 END AS p
  FROM (SELECT user_id, n, unnest(range((n + 63) // 64)) AS k FROM (SELECT user_id, count(*) AS n FROM events GROUP BY 1)))"""


def by_panel(body: str, columns: str) -> str:
    """SQL of each user's panels with the rows that ``body``, SQL on the worked example's tasks, has for the panel's grid."""
    grids = f"SELECT 1 AS p, * FROM ({body.replace(VALUES, ONE_VALUES)}) UNION ALL SELECT 2 AS p, * FROM ({body})"
    return f"WITH {PANELS}, grids AS MATERIALIZED ({grids}) SELECT user_id, panel, {columns} FROM panels JOIN grids USING (p)"


def panels(s: SparkSession, d: str) -> DataFrame:
    """(user_id, panel, p): a row for each panel of 64 rows of a user's events, and its tile rows."""
    n = T.load(s, d, "events").groupBy("user_id").agg(F.count("*").alias("n"))
    cut = n.select("user_id", "n", F.explode(F.sequence(F.lit(0).cast("long"), F.expr("(n + 63) div 64 - 1"))).alias("panel"))
    return cut.select("user_id", "panel", F.when(F.expr("n - 64 * panel > 32"), 2).otherwise(1).alias("p"))


def on_panels(s: SparkSession, d: str, rows, schema: str) -> DataFrame:
    """Each panel with the rows that ``rows`` makes of the ledger of its grid; there are two grids, so their rows are broadcast."""
    made = s.createDataFrame([(p, *r) for p in (1, 2) for r in rows(p)], f"p int, {schema}")
    return panels(s, d).join(F.broadcast(made), "p").drop("p")


def listed(p: int) -> list[tuple]:
    return [(t.seq, t.op, ",".join(t.ins), ",".join(t.outs)) for t in L.plan_utv(p, 2)]


def example(s: SparkSession) -> DataFrame:
    return L.task_frame(s, L.plan_utv(2, 2))


register("ledger_2x2_tasks", by_panel(f"WITH {TASKS} SELECT seq, op, ins, outs FROM tasks", "seq, op, ins, outs"))(
    lambda s, d: on_panels(s, d, listed, "seq int, op string, ins string, outs string")
)
register("ledger_direct_io", by_panel(f"WITH {TASKS} SELECT seq, CAST({COUNT.format('ins')} AS BIGINT) AS reads, CAST({COUNT.format('outs')} AS BIGINT) AS writes FROM tasks", "seq, reads, writes"))(
    lambda s, d: on_panels(s, d, lambda p: [(x["seq"], x["reads"], x["writes"]) for x in L.replay(L.plan_utv(p, 2), "direct")], "seq int, reads bigint, writes bigint")
)
LRU_CASES = [(7, 6), (7, 22), (8, 22), (16, 22)]
TOUCH = f"""{TASKS}, touch AS MATERIALIZED (
  SELECT seq, seq * 100 + pos - 1 AS tick, blocks[pos] AS block, pos <= n_in AS is_in FROM (
    SELECT seq, {COUNT.format('ins')} AS n_in, list_concat(CASE WHEN ins = '' THEN [] ELSE string_split(ins, ',') END, string_split(outs, ',')) AS blocks,
           unnest(range(1, CAST(len(list_concat(CASE WHEN ins = '' THEN [] ELSE string_split(ins, ',') END, string_split(outs, ','))) AS BIGINT) + 1)) AS pos FROM tasks)
)"""
# When a block goes: as soon as as many other blocks as there are slots were touched since its last touch.
LRU = f"""{TOUCH}, span AS MATERIALIZED (
  SELECT a.tick AS l, b.tick AS t, count(DISTINCT c.block) AS d FROM touch a JOIN touch b ON b.tick > a.tick JOIN touch c ON c.tick > a.tick AND c.tick <= b.tick GROUP BY 1, 2
), gone AS (SELECT slots, l, min(t) AS at FROM span, sizes WHERE d >= slots GROUP BY 1, 2),
chain AS (SELECT s.slots, t.*, lead(tick) OVER w AS after, lag(tick) OVER w AS before FROM touch t, sizes s WINDOW w AS (PARTITION BY s.slots, block ORDER BY tick)),
life AS (SELECT c.*, g.at AS leaves, (g.at IS NOT NULL AND (after IS NULL OR g.at < after)) AS ends, (before IS NULL OR coalesce(b.at < c.tick, false)) AS miss
  FROM chain c LEFT JOIN gone g ON g.slots = c.slots AND g.l = c.tick LEFT JOIN gone b ON b.slots = c.slots AND b.l = c.before),
stay AS MATERIALIZED (SELECT *, sum(CAST(miss AS INTEGER)) OVER (PARTITION BY slots, block ORDER BY tick ROWS UNBOUNDED PRECEDING) AS visit FROM life)"""
LRU_IO = f"""WITH sizes(slots) AS (VALUES (7), (8), (16)), cases(slots, tasks) AS (VALUES {', '.join(map(str, LRU_CASES))}), {LRU},
out AS (SELECT slots, block, visit, max(CASE WHEN ends THEN leaves END) // 100 AS seq, bool_or(NOT is_in) AS dirty FROM stay GROUP BY 1, 2, 3)
SELECT CAST(c.slots AS BIGINT) AS slots, CAST(c.tasks AS BIGINT) AS tasks, (SELECT count(*) FROM stay s WHERE s.slots = c.slots AND s.seq < c.tasks AND s.miss AND s.is_in) AS reads,
  (SELECT count(*) FROM out o WHERE o.slots = c.slots AND o.seq < c.tasks AND o.dirty) AS writes FROM cases c"""
LRU_TRACE = f"""WITH sizes(slots) AS (VALUES (7)), {LRU},
ends AS (SELECT DISTINCT seq AS e FROM touch),
held AS (SELECT e, block, max(tick) AS last, row_number() OVER (PARTITION BY e ORDER BY max(tick) DESC) AS age FROM touch JOIN ends ON seq <= e GROUP BY 1, 2),
inside AS (SELECT h.*, s.visit FROM held h JOIN stay s ON s.block = h.block AND s.tick = h.last WHERE h.age <= 7),
soiled AS (SELECT i.e, i.block, bool_or(NOT s.is_in) AS dirty FROM inside i JOIN stay s ON s.block = i.block AND s.visit = i.visit AND s.seq <= i.e GROUP BY 1, 2),
out AS (SELECT block, visit, max(CASE WHEN ends THEN leaves END) // 100 AS seq, bool_or(NOT is_in) AS dirty FROM stay GROUP BY 1, 2)
SELECT CAST(i.e AS INTEGER) AS seq, string_agg(i.block, ',' ORDER BY i.last) AS slot, CAST((SELECT count(*) FROM stay s WHERE s.seq = i.e AND s.miss AND s.is_in) AS INTEGER) AS reads,
  CAST((SELECT count(*) FROM out o WHERE o.seq = i.e AND o.dirty) AS INTEGER) AS writes, CAST((SELECT count(*) FROM soiled d WHERE d.e = i.e AND d.dirty) AS INTEGER) AS dirty
FROM inside i GROUP BY i.e"""


@register("ledger_lru_io", by_panel(LRU_IO, "slots, tasks, reads, writes"))
def ledger_lru(s: SparkSession, d: str) -> DataFrame:
    return on_panels(s, d, lambda p: [(a, b, *L.totals(L.replay(L.plan_utv(p, 2), "lru", a), b)) for a, b in LRU_CASES], "slots bigint, tasks bigint, reads bigint, writes bigint")


@register("ledger_lru_trace", by_panel(LRU_TRACE, "seq, slot, reads, writes, dirty"))
def ledger_lru_trace(s: SparkSession, d: str) -> DataFrame:
    def rows(p: int) -> list[tuple]:
        return [(x["seq"], ",".join(x["slot"]), x["reads"], x["writes"], x["dirty"]) for x in L.replay(L.plan_utv(p, 2), "lru", 7)]

    return on_panels(s, d, rows, "seq int, slot string, reads int, writes int, dirty int")


def reuse(s: SparkSession, slots: int = 7) -> DataFrame:
    """Distinct blocks touched since a block's last touch: at ``slots`` or more of them an LRU cache has lost it."""
    touches = example(s).select("seq", F.posexplode(F.concat("ins", "outs")).alias("pos", "block"), F.size("ins").alias("n_in"))
    touches = touches.withColumn("tick", F.col("seq") * 100 + F.col("pos")).withColumn("is_in", F.col("pos") < F.col("n_in"))
    last = touches.withColumn("before", F.lag("tick").over(Window.partitionBy("block").orderBy("tick")))
    other = touches.select(F.col("tick").alias("o_at"), F.col("block").alias("o_block"))
    between = last.join(F.broadcast(other), (F.col("o_at") > F.col("before")) & (F.col("o_at") < F.col("tick")), "left")
    dist = between.groupBy("seq", "tick", "block", "is_in", "before").agg(F.count_distinct("o_block").alias("dist"))
    miss = F.col("is_in") & (F.col("before").isNull() | (F.col("dist") >= slots))
    return dist.select("seq", "block", F.col("tick").cast("bigint").alias("tick"), F.when(F.col("before").isNull(), -1).otherwise(F.col("dist")).cast("bigint").alias("dist"), miss.cast("int").alias("miss"))


REUSE = f"""WITH {TASKS}, touch AS (
  SELECT seq, seq * 100 + pos - 1 AS tick, blocks[pos] AS block, pos <= n_in AS is_in FROM (
    SELECT seq, {COUNT.format('ins')} AS n_in, list_concat(CASE WHEN ins = '' THEN [] ELSE string_split(ins, ',') END, string_split(outs, ',')) AS blocks,
           unnest(range(1, CAST(len(list_concat(CASE WHEN ins = '' THEN [] ELSE string_split(ins, ',') END, string_split(outs, ','))) AS BIGINT) + 1)) AS pos FROM tasks)
), last AS (SELECT *, lag(tick) OVER (PARTITION BY block ORDER BY tick) AS before FROM touch)
SELECT l.seq, l.block, CAST(l.tick AS BIGINT) AS tick,
  CAST(CASE WHEN l.before IS NULL THEN -1 ELSE (SELECT count(DISTINCT o.block) FROM touch o WHERE o.tick > l.before AND o.tick < l.tick) END AS BIGINT) AS dist,
  CAST(l.is_in AND (l.before IS NULL OR (SELECT count(DISTINCT o.block) FROM touch o WHERE o.tick > l.before AND o.tick < l.tick) >= 7) AS INTEGER) AS miss
FROM last l"""
register("ledger_reuse_distance", by_panel(REUSE, "seq, block, tick, dist, miss"))(
    lambda s, d: on_panels(s, d, lambda p: [(x["seq"], x["block"], x["tick"], x["dist"], int(x["is_in"] and (x["dist"] < 0 or x["dist"] >= 7))) for x in L.reuse_distances(L.plan_utv(p, 2))], "seq int, block string, tick bigint, dist bigint, miss int")
)
register("win_reuse_distance", REUSE)(lambda s, d: reuse(s))
# Each user's events as one grid of tiles of 8 rows, and 3 or 6 tile columns.
QR_COUNTS = """SELECT CAST(m AS BIGINT) AS m, CAST(n AS BIGINT) AS n, op, CAST(sum(users) AS BIGINT) AS users, CAST(sum(users * c) AS BIGINT) AS tasks FROM (
  SELECT m, n, op, CASE WHEN i = 0 THEN users ELSE 0 END AS users, users AS u, CASE op WHEN 'qr_dense' THEN 1 WHEN 'qr_stacked' THEN m - i - 1 WHEN 'left_dense' THEN n - i - 1 ELSE (m - i - 1) * (n - i - 1) END AS c
  FROM (SELECT (k + 7) // 8 AS m, count(*) AS users FROM (SELECT count(*) AS k FROM events GROUP BY user_id) GROUP BY 1), (VALUES (3), (6)) AS g(n),
    (VALUES ('qr_dense'), ('qr_stacked'), ('left_dense'), ('left_stacked')) AS o(op), range(6) AS r(i) WHERE i < least(m, n))
GROUP BY 1, 2, 3 HAVING sum(u * c) > 0""".replace("sum(users * c)", "sum(u * c)")


def on_grids(s: SparkSession, d: str, b: int, rows, schema: str) -> DataFrame:
    """``rows(m, users)`` for each number m of tile rows of ``b`` that users' events have, made in Spark's tasks: a task for each such m."""
    n = T.load(s, d, "events").groupBy("user_id").agg(F.count("*").alias("n"))
    grids = n.groupBy(F.expr(f"(n + {b - 1}) div {b}").alias("m")).agg(F.count("*").alias("users"))

    def run(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        made = [r for m, users in zip(t["m"].to_pylist(), t["users"].to_pylist(), strict=True) for r in rows(m, users)]
        return pa.table([pa.array(c, x) for c, x in zip(zip(*made), types)], names=names)

    names = [c.split()[0] for c in schema.split(", ")]
    types = [{"bigint": pa.int64(), "int": pa.int32(), "string": pa.string(), "boolean": pa.bool_(), "double": pa.float64()}[c.split()[1]] for c in schema.split(", ")]
    return grids.groupBy("m").applyInArrow(run, schema)


def counts(s: SparkSession, plans: list[tuple], *names: str) -> DataFrame:
    rows = [(*key, t.op) for key, tasks in plans for t in tasks]
    return s.createDataFrame(rows, f"{names[0]} bigint, {names[1]} bigint, op string").groupBy(*names, "op").agg(F.count("*").alias("tasks"))


register("ledger_qr_counts", QR_COUNTS)(
    lambda s, d: on_grids(s, d, 8, lambda m, users: [(m, n, op, users, users * k) for n in (3, 6) for op, k in Counter(t.op for t in L.plan_qr(m, n)).items()], "m bigint, n bigint, op string, users bigint, tasks bigint")
)
UTV_COUNTS = """SELECT CAST(p AS BIGINT) AS p, CAST(q AS BIGINT) AS q, op, CAST(sum(c) AS BIGINT) AS tasks FROM (
  SELECT p, q, op, CASE op WHEN 'draw' THEN k WHEN 'gemm_tn_set' THEN (1 + q) * k WHEN 'gemm_tn_add' THEN (1 + q) * k * (k - 1) WHEN 'gemm_nn_set' THEN q * k
    WHEN 'gemm_nn_add' THEN q * k * (k - 1) WHEN 'right_dense' THEN p WHEN 'right_stacked' THEN p * (k - 1) END AS c
  FROM (SELECT p, q, op, p - i AS k FROM (VALUES (2), (4)) AS a(p), (VALUES (0), (1), (2)) AS b(q), range(4) AS r(i),
    (VALUES ('draw'), ('gemm_tn_set'), ('gemm_tn_add'), ('gemm_nn_set'), ('gemm_nn_add'), ('right_dense'), ('right_stacked')) AS o(op) WHERE i < p - 1))
WHERE c > 0 GROUP BY 1, 2, 3"""
register("ledger_utv_counts", UTV_COUNTS)(
    lambda s, d: counts(s, [((p, q), L.plan_utv(p, p, q)) for p in (2, 4) for q in (0, 1, 2)], "p", "q").where("op in ('draw', 'gemm_tn_set', 'gemm_tn_add', 'gemm_nn_set', 'gemm_nn_add', 'right_dense', 'right_stacked')")
)


@register("ledger_overlap_makespan")
def ledger_makespan(s: SparkSession, d: str) -> DataFrame:
    """Experiment: direct, cached and overlapped, by power steps and factors kept, for the grids of users' events (8 tile columns)."""

    def rows(m: int, users: int) -> list[tuple]:
        plans = [(q, uv, L.plan_utv(m, 8, q, uv)) for q in (0, 1, 2) for uv in (False, True)]
        return [(m, users, mode, q, uv, *(float(v) for v in L.makespan(tasks, mode, 20, 1.0, 1.0, 4).values())) for q, uv, tasks in plans for mode in ("direct", "lru", "overlap")]

    return on_grids(s, d, 8, rows, "tile_rows bigint, users bigint, method string, q int, uv boolean, compute double, io double, total double, real double")


#: Tile edge at which a kernel reaches half of the machine's rate, as tall kernels' rates grow with their tiles.
HALF_RATE = 1000


def block_sizes(n: int) -> list[tuple]:
    """Block sizes at one matrix size, QR and UTV. Small blocks move more tiles and run slower kernels, large ones leave few slots
    and little to overlap."""
    memory, rate, disk, latency = 16 << 30, 1e11, 91.13e6, 0.02  # cache and disk as published
    rows = []
    for b in (2560, 5120, 7680, 10_240, 20_480):
        p, tile = -(-n // b), 8 * b * b
        plans = [("qr", 0, L.plan_qr(p, p)), *(("utv", q, L.plan_utv(p, p, q)) for q in (0, 1))]
        for method, q, tasks in plans:
            for mode in ("direct", "overlap"):
                got = L.makespan(tasks, mode, max(7, memory // tile), tile / disk + latency, b**3 / (rate * b / (b + HALF_RATE)), 1)
                rows.append((method, q, mode, b, got["compute"], got["io"], got["real"]))
    return rows


@register("ledger_block_sizes")
def ledger_block_sizes(s: SparkSession, d: str) -> DataFrame:
    """Experiment: ``block_sizes`` of square matrices as large as users' events, 10,240 rows for each 16 of them (128 events make the published size)."""
    schema = "units bigint, users bigint, method string, q int, mode string, b bigint, compute double, io double, real double"
    return on_grids(s, d, 16, lambda m, users: [(m, users, *r) for r in block_sizes(10_240 * m)], schema)


@register("ledger_schedule_trace")
def ledger_trace(s: SparkSession, d: str) -> DataFrame:
    """Start and end of each transfer and task by lane, over the whole run and over its first sixth."""
    tasks = L.plan_utv(4, 4)
    trace, level = L.replay(tasks, "overlap", 12), L.waves(tasks)
    whole = L.lanes(tasks, [t.flops for t in tasks], [float(x["reads"] + x["writes"]) for x in trace], 12, 2)
    rows = [(name, x["lane"], x["seq"], tasks[x["seq"]].op, level[x["seq"]], x["start"], x["end"]) for name, part in (("whole", whole), ("first sixth", L.window(whole, 1 / 6))) for x in part]
    return s.createDataFrame(rows, "part string, lane string, seq int, op string, wave int, start double, end double")


# the tasks of a panel's first tile column, as rule: which tile a task changes, and which are nullified after it
MASKS = f"""WITH {PANELS}, t(p, seq, op, r, c) AS (VALUES (1, 0, 'qr_dense', 0, 0), (1, 1, 'left_dense', 0, 1),
  (2, 0, 'qr_dense', 0, 0), (2, 1, 'qr_stacked', 1, 0), (2, 2, 'left_dense', 0, 1), (2, 3, 'left_stacked', 1, 1)), g AS (SELECT i AS bi, j AS bj FROM range(2) a(i), range(2) b(j))
SELECT user_id, panel, CAST(t.seq AS BIGINT) AS seq, t.op, bi, bj, CAST(bj = t.c AND bi IN (0, t.r) AS BIGINT) AS modified,
  CASE WHEN bi = 0 AND bj = 0 THEN 'triangle' WHEN bj = 0 AND bi > 0 AND t.seq >= bi THEN 'zero' ELSE 'full' END AS state FROM panels JOIN t USING (p), g WHERE bi < p"""
register("ledger_qr_masks", MASKS)(
    lambda s, d: on_panels(s, d, lambda p: [(x["seq"], x["op"], x["bi"], x["bj"], x["modified"], x["state"]) for x in L.masks([t for t in L.plan_qr(p, 2) if t.step == 0], p, 2)], "seq bigint, op string, bi bigint, bj bigint, modified bigint, state string")
)


# cost model

register("model_incore_limit", "SELECT CAST(bytes AS BIGINT) AS bytes, CAST(copies AS BIGINT) AS copies, CAST(floor(sqrt(bytes / (8.0 * copies))) AS BIGINT) AS n_max FROM (VALUES (51539607552, 1), (51539607552, 3), (134217728000, 1)) AS t(bytes, copies)")(
    lambda s, d: s.createDataFrame([(b, c, C.max_incore_n(b, c)) for b, c in ((51539607552, 1), (51539607552, 3), (134217728000, 1))], "bytes bigint, copies bigint, n_max bigint")
)
WRITES = """SELECT method, CAST(n AS BIGINT) AS n, CAST(b AS BIGINT) AS b, CAST(sum(CASE method WHEN 'right' THEN (n - i * b) * (n - i * b) ELSE n * least(b, n - i * b) END) AS BIGINT) AS elements
FROM (VALUES ('left'), ('right')) AS m(method), (VALUES (1000, 100), (4096, 256), (1000, 300)) AS g(n, b), range(100) AS r(i) WHERE i * b < n GROUP BY 1, 2, 3"""
register("model_write_volume", WRITES)(lambda s, d: s.createDataFrame([(m, n, b, C.write_volume(m, n, b)) for m in ("left", "right") for n, b in ((1000, 100), (4096, 256), (1000, 300))], "method string, n bigint, b bigint, elements bigint"))
FLOPS = "SELECT method, CAST(q AS INTEGER) AS q, CAST(uv AS BOOLEAN) AS uv, round(CASE method WHEN 'qr' THEN 4 / 3.0 + CASE WHEN uv THEN 4 / 3.0 ELSE 0 END ELSE 4 + 4 * q / 3.0 + CASE WHEN uv THEN 4 ELSE 0 END END, 6) + 0.0 AS n3 FROM (VALUES ('qr', 0), ('utv', 0), ('utv', 1), ('utv', 2)) AS t(method, q), (VALUES (false), (true)) AS u(uv)"
register("model_flops", FLOPS.replace("AS n3", "AS n3").replace("round(CASE", "round(CAST(CASE").replace("END END, 6)", "END END AS DOUBLE), 6)"))(
    lambda s, d: rounded(s.createDataFrame([(m, q, uv, C.flops(m, 1.0, q, uv)) for m, q in (("qr", 0), ("utv", 0), ("utv", 1), ("utv", 2)) for uv in (False, True)], "method string, q int, uv boolean, n3 double"), "n3")
)
# Published seconds of computation, I/O and real time by machine and size.
TIMES = [("ut", 348_160, 229627.6, 41312.9, 229910.0), ("ucm", 143_360, 34165.5, 38253.5, 43326.0)]
TIME_ROWS = ", ".join(f"('{m}', {n}, {a}, {b}, {c})" for m, n, a, b, c in TIMES)


@register(
    "model_table1_ratios",
    f"SELECT machine, round(CAST(c + i AS DOUBLE), 3) AS total, round(CAST(r AS DOUBLE) / c, 6) AS real_by_compute, round(CAST(c AS DOUBLE) / i, 6) AS compute_by_io, round(CAST(greatest(c, i) AS DOUBLE) / r, 6) AS overlap, round(CAST(r AS DOUBLE) / power(n, 3) * 1e10, 6) AS scaled FROM (VALUES {TIME_ROWS}) AS t(machine, n, c, i, r)",
)
def model_ratios(s: SparkSession, d: str) -> DataFrame:
    t = s.createDataFrame(TIMES, "machine string, n bigint, c double, i double, r double")
    return t.select("machine", F.round(F.col("c") + F.col("i"), 3).alias("total"), F.round(F.col("r") / F.col("c"), 6).alias("real_by_compute"), F.round(F.col("c") / F.col("i"), 6).alias("compute_by_io"), F.round(F.greatest("c", "i") / F.col("r"), 6).alias("overlap"), F.round(F.col("r") / F.pow("n", F.lit(3)) * 1e10, 6).alias("scaled"))


@register("model_decomposed_times")
def model_decomposed(s: SparkSession, d: str) -> DataFrame:
    """Experiment: the ledger replayed at both published sizes with rates taken from the published times."""
    rows = []
    for machine, grid, slots, compute, io, real in (("ut", 17, 81, *TIMES[0][2:]), ("ucm", 7, 10, *TIMES[1][2:])):
        tasks = L.plan_utv(grid, grid)
        unit = L.makespan(tasks, "overlap", slots)
        got = L.makespan(tasks, "overlap", slots, io / unit["io"], compute / unit["compute"], 1)
        rows.append((machine, got["compute"], got["io"], got["sum"], got["real"], real))
    return s.createDataFrame(rows, "machine string, compute double, io double, total double, real double, published double")


# tiles


def tile_matrix(s: SparkSession, d: str, m: int, b: int) -> DataFrame:
    return X.store(T.to_tiles(T.entries(T.emb(s, d)), b, 64, m))


def tileqr(s: SparkSession, d: str, mode: str) -> DataFrame:
    """All rows of the matrix as a grid of tiles; a tree over each tile column."""
    m, b = T.load(s, d, "embeddings").count(), 32
    run = X.run_waves(L.plan_qr(-(-m // b), 2, True), tile_matrix(s, d, m, b), m, 64, b, mode=mode)
    top = run.tiles("A").where("name rlike '^A_[01]_'").withColumns({"bi": F.split("name", "_")[1].cast("int"), "bj": F.split("name", "_")[2].cast("int")})
    r = T.from_tiles(top.select("bi", "bj", "nr", "nc", "data"), b).where("row_id <= col_id")
    # signs as of a triangle whose diagonal is not negative
    sign = r.where("row_id = col_id").select("row_id", F.when(F.col("v") < 0, -1.0).otherwise(1.0).alias("sign"))
    signed = r.join(F.broadcast(sign), "row_id")  # 64 rows
    return rounded(signed.select(F.col("row_id").alias("i"), F.col("col_id").cast("bigint").alias("j"), (F.col("v") * F.col("sign")).alias("r_ij")), "r_ij")


register("tileqr_emb_r", G.fixed_r(G.EMB, 64))(lambda s, d: tileqr(s, d, "direct"))
register("tileqr_emb_r_overlap", G.fixed_r(G.EMB, 64))(lambda s, d: tileqr(s, d, "overlap"))


@register("tileqr_line4_r", G.fixed_r(G.LINE4, 4, "(SELECT sqrt(sum(l_extendedprice * l_extendedprice)) FROM lineitem)"))
def tileqr_line4(s: SparkSession, d: str) -> DataFrame:
    """One tile column: a chain of dense and stacked QRs inside tasks, a tree over them."""
    m = Tall(T.line4(s, d))

    def chain(_, a: np.ndarray) -> np.ndarray:
        r = K.reflectors(a[:1000])[0][:4]
        for i in range(1000, len(a), 1000):
            r = K.stacked(np.vstack([r, np.zeros((4 - len(r), 4))]), a[i : i + 1000])[0]
        return r

    return triangle_frame(s, K.positive(m.reduce(chain, K.r_only)), float(m.column_norms()[1]))


EMB_GRAM = f"WITH {G.gram(G.EMB)} SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, round(v, 6) + 0.0 AS g FROM g0"


def tile_gram(s: SparkSession, d: str, mode: str) -> DataFrame:
    """Tile UTV of the whole matrix's triangle, R = U T V': V T'T V' is A'A."""
    b = 32
    r = Tall(T.emb(s, d)).triangle()
    tasks = L.plan_utv(2, 2, 1, True)
    held = X.split(r, b) | X.split(np.eye(64), b, "U") | X.split(np.eye(64), b, "V")
    if mode == "memory":
        held = X.run_local(tasks, held, 64, 64, b, workers=4)
    start = s.createDataFrame([(k, v.shape[0], v.shape[1], bytearray(np.ascontiguousarray(v).tobytes())) for k, v in held.items() if k[0] in "AUV"], X.STORE)
    done = start if mode == "memory" else X.run_waves(tasks, start, 64, 64, b, mode=mode).tiles()
    t, v = (X.grid(done, name) for name in "AV")
    x = X.multiply(t, T.transpose_tiles(v))
    return rounded(T.from_tiles(X.multiply(T.transpose_tiles(x), x), b).select(F.col("row_id").alias("i"), F.col("col_id").cast("bigint").alias("j"), F.col("v").alias("g")), "g")


for mode in ("memory", "direct", "overlap"):
    register(f"tileutv_emb_gram_{mode}", EMB_GRAM)(lambda s, d, mode=mode: tile_gram(s, d, mode))


@register("set_except_rows", f"WITH {TASKS}, touched AS (SELECT seq, unnest(string_split(ins, ',')) AS block FROM tasks WHERE ins <> ''), changed AS (SELECT seq, unnest(string_split(outs, ',')) AS block FROM tasks) SELECT seq, block FROM touched EXCEPT SELECT seq, block FROM changed")
def set_except(s: SparkSession, d: str) -> DataFrame:
    t = example(s)
    return t.select("seq", F.explode("ins").alias("block")).exceptAll(t.select("seq", F.explode("outs").alias("block"))).distinct()


@register("sort_global_tasks", f"WITH {TASKS} SELECT CAST(row_number() OVER (ORDER BY op, seq) AS BIGINT) AS pos, seq FROM tasks")
def sort_tasks(s: SparkSession, d: str) -> DataFrame:
    ordered = with_index(example(s).select(F.struct("op", "seq").alias("row_id"), "seq"), "row_id", "pos")
    return ordered.select((F.col("pos") + 1).alias("pos"), "seq")


SETS = f"""WITH x AS ({by_panel(f"WITH {TASKS} SELECT op, CAST({COUNT.format('ins')} AS INTEGER) AS n_in FROM tasks", "op, n_in")})
SELECT op, n_in, CAST(grouping(op, n_in) AS BIGINT) AS g, count(*) AS n FROM x GROUP BY GROUPING SETS ((op), (n_in), ())"""


@register("agg_grouping_sets", SETS)
def agg_grouping_sets(s: SparkSession, d: str) -> DataFrame:
    on_panels(s, d, lambda p: [(t.op, len(t.ins)) for t in L.plan_utv(p, 2)], "op string, n_in int").createOrReplaceTempView("ledger_tasks__")
    return s.sql("SELECT op, n_in, grouping_id(op, n_in) AS g, count(*) AS n FROM ledger_tasks__ GROUP BY GROUPING SETS ((op), (n_in), ())")
