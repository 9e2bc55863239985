"""UDFs, formats, bucketed joins, the Python data source and streams."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilerank.functions import vectors as V
from tilerank.functions.keyed import gaussian_sql, gaussians
from tilerank.operators.router import factorize
from tilerank.operators.tiles import multiply_thin
from tilerank.sources import formats
from tilerank.sources import tables as T
from tilerank.streaming import events as S

from . import sqlgen as G
from .methods import pivot_frame, triangle_frame
from .relational import r6

QUERIES: dict = {}
ORACLES: dict = {}


def q(oracle: str | None = None):
    def put(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return put


def tiles(s: SparkSession, d: str, b: int = 24) -> DataFrame:
    return T.to_tiles(T.supppart(s, d), b, 64, T.load(s, d, "supplier").count())


SP = G.SUPPPART


@q(f"SELECT CAST(row_id // 24 AS INTEGER) AS bi, CAST(col_id // 24 AS INTEGER) AS bj, round(sqrt(sum(v * v)), 5) + 0.0 AS norm FROM ({SP}) GROUP BY 1, 2")
def udf_tile_norm(s: SparkSession, d: str) -> DataFrame:
    return tiles(s, d).select("bi", "bj", (F.round(V.tile_norm("data"), 5) + 0.0).alias("norm"))


@q(f"SELECT CAST(col_id // 24 AS INTEGER) AS bj, sum(v) + 0.0 AS s FROM ({SP}) GROUP BY 1")
def udaf_tile_sum(s: SparkSession, d: str) -> DataFrame:
    return tiles(s, d).groupBy("bj").agg(V.tile_sum("data").alias("s"))


def logdet_sql() -> str:
    parts = ["e AS MATERIALIZED (SELECT label, vec_id AS row_id, unnest(range(8)) AS col_id, CAST(unnest(embedding[1:8]) AS DOUBLE) AS v FROM embeddings)"]
    parts.append("g0 AS MATERIALIZED (SELECT a.label, a.col_id AS i, b.col_id AS j, sum(a.v * b.v) AS v FROM e a JOIN e b USING (label, row_id) GROUP BY 1, 2, 3)")
    for t in range(8):
        parts.append(f"p{t} AS MATERIALIZED (SELECT label, v AS d FROM g{t} WHERE i = {t} AND j = {t})")
        if t < 7:
            parts.append(f"g{t + 1} AS MATERIALIZED (SELECT g.label, g.i, g.j, g.v - c.v * r.v / p.d AS v FROM g{t} g JOIN p{t} p USING (label) JOIN g{t} c ON c.label = g.label AND c.i = g.i AND c.j = {t} JOIN g{t} r ON r.label = g.label AND r.i = {t} AND r.j = g.j WHERE g.i > {t} AND g.j > {t})")
    total = " + ".join(f"ln(p{t}.d)" for t in range(8))
    joins = " ".join(f"JOIN p{t} USING (label)" for t in range(1, 8))
    return f"WITH {', '.join(parts)} SELECT label, round(0.5 * ({total}), 5) + 0.0 AS logdet FROM p0 {joins}"


@q(logdet_sql())
def udf_grouped_qr(s: SparkSession, d: str) -> DataFrame:
    """Triangle of each label's rows over the first eight columns. Groups are label-sized; rows are reduced to triangles before they meet."""

    def leaf(batches):
        for b in batches:
            labels, x = b.column(0).to_numpy(zero_copy_only=False), np.array(b.column(1).to_pylist())
            found = [(int(k), np.linalg.qr(x[labels == k], mode="r")) for k in np.unique(labels)]
            yield pa.RecordBatch.from_arrays([pa.array([k for k, _ in found], pa.int32()), pa.array([r.tolist() for _, r in found], pa.list_(pa.list_(pa.float64())))], names=["label", "r"])

    def top(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        r = np.linalg.qr(np.vstack([np.array(x) for x in t["r"].to_pylist()]), mode="r")
        return pa.table({"label": pa.array([key[0].as_py()], pa.int32()), "logdet": [float(np.log(np.abs(np.diag(r))).sum())]})

    rows = T.load(s, d, "embeddings").select("label", F.slice(F.col("embedding").cast("array<double>"), 1, 8).alias("x"))
    return rows.mapInArrow(leaf, "label int, r array<array<double>>").groupBy("label").applyInArrow(top, "label int, logdet double").select("label", (F.round("logdet", 5) + 0.0).alias("logdet"))


NRM = f"SELECT row_id AS vec_id, round(sqrt(sum(v * v)), 6) + 0.0 AS nrm FROM ({G.EMB}) GROUP BY 1"


@q(NRM)
def udf_partition_map(s: SparkSession, d: str) -> DataFrame:
    return T.emb(s, d).mapInArrow(V.row_norms, "row_id bigint, nrm double").select(F.col("row_id").alias("vec_id"), r6(F.col("nrm"), "nrm"))


@q(NRM)
def sql_registered_fn(s: SparkSession, d: str) -> DataFrame:
    V.register_all(s)
    T.emb(s, d).createOrReplaceTempView("emb_rows__")
    return s.sql("SELECT row_id AS vec_id, round(array_norm(x), 6) + 0.0 AS nrm FROM emb_rows__")


@q(f"WITH e AS ({SP}), g AS (SELECT DISTINCT row_id // 24 AS bi, col_id // 24 AS bj FROM e), m AS (SELECT count(*) AS m FROM supplier) SELECT r AS row_id, CAST(c AS BIGINT) AS col, coalesce(v, 0) + 0.0 AS v FROM (SELECT unnest(range(m)) AS r FROM m), (SELECT unnest(range(64)) AS c) JOIN g ON g.bi = r // 24 AND g.bj = c // 24 LEFT JOIN e ON e.row_id = r AND e.col_id = c")
def udtf_tile_entries(s: SparkSession, d: str) -> DataFrame:
    V.register_all(s)
    tiles(s, d).createOrReplaceTempView("tiles__")
    return s.sql("SELECT e.row_id, e.col, e.v FROM tiles__ t, LATERAL tile_entries(t.data, t.bi, t.bj, t.nr, t.nc, 24) e")


@q(f"SELECT CAST(r AS BIGINT) AS row_id, CAST(c AS BIGINT) AS col, round({gaussian_sql(7, 'r', 'c')}, 6) + 0.0 AS g FROM (SELECT unnest(range(10)) AS r), (SELECT unnest(range(4)) AS c)")
def udtf_keyed_gaussians(s: SparkSession, d: str) -> DataFrame:
    V.register_all(s)
    return s.sql("SELECT row_id, col, round(g, 6) + 0.0 AS g FROM keyed_gaussians(10, 4, 7)")


def round_trip(fmt: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        df = T.load(s, d, "supplier")
        path = f"{S.root_of(s)}/{fmt}"
        formats.write_matrix(df, path, fmt)
        return formats.read_matrix(s, path, fmt, df.schema)

    return run


for fmt in ("parquet", "csv", "json", "orc"):
    QUERIES[f"io_roundtrip_{fmt}"], ORACLES[f"io_roundtrip_{fmt}"] = round_trip(fmt), "SELECT * FROM supplier"


@q(f"SELECT CAST(col_id AS BIGINT) AS col, sum(v) + 0.0 AS s FROM ({SP}) GROUP BY 1")
def io_bucketed_join(s: SparkSession, d: str) -> DataFrame:
    """Both sides bucketed by the contraction index: the join needs no exchange."""
    name = f"bucketed_{uuid.uuid4().hex}"
    e = T.supppart(s, d)
    e.write.bucketBy(8, "col_id").saveAsTable(name)
    s.range(64).select(F.col("id").cast("int").alias("col_id"), F.lit(1.0).alias("w")).write.bucketBy(8, "col_id").saveAsTable(f"{name}_w")
    j = s.table(name).join(s.table(f"{name}_w").hint("merge"), "col_id")
    return j.groupBy("col_id").agg(F.sum(F.col("v") * F.col("w")).alias("s")).select(F.col("col_id").cast("bigint").alias("col"), "s")


@q("SELECT CAST(month(l_shipdate) AS INTEGER) AS m, count(*) AS n, sum(l_quantity) + 0.0 AS qty FROM lineitem WHERE year(l_shipdate) = 1996 AND l_discount > 0.05 GROUP BY 1")
def io_pushdown_filter(s: SparkSession, d: str) -> DataFrame:
    li = T.load(s, d, "lineitem").where((F.col("l_shipdate") >= F.lit("1996-01-01").cast("timestamp_ntz")) & (F.col("l_shipdate") < F.lit("1997-01-01").cast("timestamp_ntz")) & (F.col("l_discount") > 0.05))
    return li.groupBy(F.month("l_shipdate").alias("m")).agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"))


@q()
def io_datasource_tiles(s: SparkSession, d: str) -> DataFrame:
    """Norms of the tiles of A G: the embedding matrix and keyed random tiles that a Python data source makes."""
    formats.register(s)
    m = T.load(s, d, "embeddings").count()
    a = T.to_tiles(T.entries(T.emb(s, d)), 16, 64, m)
    g = s.read.format("tilematrix").option("m", "64").option("n", "40").option("b", "16").load()
    return multiply_thin(a, g, -(-m // 16), 3).select("bi", "bj", (F.round(V.tile_norm("data"), 6) + 0.0).alias("norm"))


# streams


@q("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, round(sum(value * value), 3) + 0.0 AS e FROM events GROUP BY 1, 2")
def stream_norms_tumbling(s: SparkSession, d: str) -> DataFrame:
    out = S.settle(S.tumbling_norms(stamped(s, d)), "complete")
    return out.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", (F.round("e", 3) + 0.0).alias("e"))


def stamped(s: SparkSession, d: str) -> DataFrame:
    return S.read_events(s, d).withColumn("ts", F.col("ts").cast("timestamp"))


@q("SELECT CAST(epoch(time_bucket(INTERVAL 2 HOUR, ts)) - 7200 * k AS BIGINT) AS start, count(*) AS n FROM events, (SELECT unnest(range(3)) AS k) GROUP BY 1")
def stream_norms_sliding(s: SparkSession, d: str) -> DataFrame:
    out = S.settle(S.sliding_counts(stamped(s, d)), "complete")
    return out.select(F.unix_timestamp("window.start").alias("start"), "n")


SESSION = """WITH m AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
n AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM m)
SELECT user_id, CAST(epoch_us(min(ts)) // 1000000 AS BIGINT) AS start, count(*) AS n FROM n GROUP BY user_id, k"""


@q(SESSION)
def stream_session(s: SparkSession, d: str) -> DataFrame:
    out = S.settle(S.sessions(stamped(s, d)), "complete")
    return out.select("user_id", F.floor(F.unix_micros("session_window.start") / 1_000_000).alias("start"), "n")


@q("SELECT event_type, CAST(hour(ts) AS INTEGER) AS h, round(sum(value * value), 3) + 0.0 AS g FROM events GROUP BY 1, 2")
def stream_gram(s: SparkSession, d: str) -> DataFrame:
    return S.settle(S.hour_gram(stamped(s, d)), "complete").select("event_type", "h", (F.round("g", 3) + 0.0).alias("g"))


@q(f"SELECT user_id, CAST(s AS BIGINT) AS s, round(sum(value * {gaussian_sql(5, 'event_id', 's')}), 4) + 0.0 AS y FROM events, (SELECT unnest(range(4)) AS s) GROUP BY 1, 2")
def stream_sketch_state(s: SparkSession, d: str) -> DataFrame:
    """Sketches that a stateful processor keeps for each user, summed over the hours."""
    with S.processors(s):
        out = S.settle(S.user_sketch(stamped(s, d), 4, 5), "update", ["user_id"])
    each = out.select("user_id", F.posexplode("y").alias("at", "y")).groupBy("user_id", F.floor(F.col("at") / 24).alias("s")).agg(F.sum("y").alias("y"))
    return each.select("user_id", "s", (F.round("y", 4) + 0.0).alias("y"))


FIRST_PIVOT = f"""WITH y AS (SELECT user_id, hour(ts) AS h, s, sum(value * {gaussian_sql(5, 'event_id', 's')}) AS y FROM events, (SELECT unnest(range(4)) AS s) GROUP BY 1, 2, 3),
n AS (SELECT user_id, h, sum(y * y) AS e FROM y GROUP BY 1, 2)
SELECT user_id, CAST(h AS INTEGER) AS pivot FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY e DESC, h) AS rn FROM n) WHERE rn = 1"""


@q(FIRST_PIVOT)
def stream_sketch_pivot(s: SparkSession, d: str) -> DataFrame:
    """The hour that each user's sketch in state would pivot on first."""
    with S.processors(s):
        out = S.settle(S.user_sketch(stamped(s, d), 4, 5), "update", ["user_id"])
    return out.select("user_id", F.get("pivots", F.lit(0)).alias("pivot"))


R_EVENTS = G.unpivot(["1.0", "value / 100", "hour(ts) / 10.0"], "events")


@q(G.fixed_r(R_EVENTS, 3))
def stream_r_incremental(s: SparkSession, d: str) -> DataFrame:
    e = stamped(s, d).select("event_id", F.lit(1.0).alias("one"), (F.col("value") / 100).alias("v"), (F.hour("ts") / 10.0).alias("h"))
    return triangle_frame(s, S.incremental_triangle(e, ["one", "v", "h"]))


@q("SELECT event_id, round(value / t, 6) + 0.0 AS share FROM events JOIN (SELECT user_id, sum(value) AS t FROM events GROUP BY 1) USING (user_id)")
def stream_join_static(s: SparkSession, d: str) -> DataFrame:
    static = T.load(s, d, "events").groupBy("user_id").agg(F.sum("value").alias("t"))
    return S.settle(stamped(s, d).join(static, "user_id").select("event_id", r6(F.col("value") / F.col("t"), "share")), "append")


@q("SELECT p.event_id AS p, v.event_id AS v FROM events p JOIN events v ON p.user_id = v.user_id AND p.event_type = 'purchase' AND v.event_type = 'view' AND v.ts <= p.ts AND v.ts >= p.ts - INTERVAL 1 HOUR")
def stream_join_stream(s: SparkSession, d: str) -> DataFrame:
    p = stamped(s, d).where("event_type = 'purchase'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("p"), F.col("user_id").alias("u"), F.col("ts").alias("pt"))
    v = stamped(s, d).where("event_type = 'view'").withWatermark("ts", "1 hour").select(F.col("event_id").alias("v"), F.col("user_id").alias("w"), F.col("ts").alias("vt"))
    return S.settle(p.join(v, F.expr("u = w AND vt <= pt AND vt >= pt - INTERVAL 1 HOUR")).select("p", "v"), "append")


@q("SELECT count(*) AS n FROM events")
def stream_dedup(s: SparkSession, d: str) -> DataFrame:
    """The same rows twice, counted once."""
    twice = stamped(s, d).withColumn("k", F.explode(F.array(F.lit(1), F.lit(2)))).withWatermark("ts", "1 hour")
    return S.settle(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "append").agg(F.count("*").alias("n"))


@q("SELECT count(*) FILTER (WHERE event_id % 10 <> 0) + 0 AS kept, count(*) FILTER (WHERE event_id % 10 = 0) + 0 AS dropped FROM events")
def stream_late_rows(s: SparkSession, d: str) -> DataFrame:
    """Each tenth row comes a year late, in the third file: the watermark of the batch before last has passed it, so it is dropped."""
    root = S.root_of(s)
    e = T.load(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    for part in ("event_id % 10 between 1 and 5", "event_id % 10 > 5"):
        e.where(part).coalesce(1).write.mode("append").parquet(f"{root}/in")
    late = e.where("event_id % 10 = 0").withColumn("ts", F.col("ts") - F.expr("INTERVAL 1 YEAR"))
    late.coalesce(1).write.mode("append").parquet(f"{root}/in")
    stream = s.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(f"{root}/in")
    once = S.settle(stream.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "ts"), "append")
    kept = once.select("event_id").join(e, "event_id", "left_semi")
    return kept.agg(F.count("*").alias("kept")).crossJoin(F.broadcast(e.agg(F.count("*").alias("total")))).select("kept", (F.col("total") - F.col("kept")).alias("dropped"))


@q("SELECT mode, strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, count(*) AS n FROM events, (VALUES ('append'), ('complete'), ('update')) AS m(mode) GROUP BY 1, 2")
def stream_output_modes(s: SparkSession, d: str) -> DataFrame:
    """Append, update and complete end with the same table, once later rows have closed all windows."""
    e = T.load(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    out = None
    for mode in ("append", "complete", "update"):
        one = S.settle(S.daily_counts(S.closing(e)), mode, ["window"]).where("window.start < timestamp'2100-01-01'")
        one = one.select(F.lit(mode).alias("mode"), F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n")
        out = one if out is None else out.union(one)
    return out


@q(G.classical_pivots(G.EMB, 8))
def sql_factorize_emb(s: SparkSession, d: str) -> DataFrame:
    """A factorization of what a SQL text returns."""
    T.load(s, d, "embeddings").createOrReplaceTempView("embeddings__")
    f = factorize(s, "SELECT vec_id, embedding FROM embeddings__", "cpqr", k=8)
    return pivot_frame(s, f, 8)


@q(f"SELECT row_id AS vec_id, CAST(col_id AS BIGINT) AS col, round(v, 6) + 0.0 AS v FROM ({G.EMB})")
def io_matrix_market(s: SparkSession, d: str) -> DataFrame:
    path = f"{S.root_of(s)}/matrix"
    e = T.entries(T.emb(s, d))
    formats.write_matrix_market(e, path, T.load(s, d, "embeddings").count(), 64)
    return formats.read_matrix_market(s, path).select(F.col("row_id").alias("vec_id"), F.col("col_id").cast("bigint").alias("col"), r6(F.col("v"), "v"))


@q(f"SELECT row_id AS vec_id, CAST(col_id AS BIGINT) AS col, round(v, 6) + 0.0 AS v FROM ({G.EMB}) WHERE row_id >= 32")
def io_npy_tiles(s: SparkSession, d: str) -> DataFrame:
    """Tiles of a .npy file by range reads; the filter on tile rows leaves out whole partitions."""
    formats.register(s)
    path = f"{S.root_of(s)}/matrix.npy"
    formats.write_npy(T.emb(s, d), path, 64)
    tiles = s.read.format("matrixfile").option("path", path).option("b", "32").load().where("bi >= 1")
    return T.from_tiles(tiles, 32).select(F.col("row_id").alias("vec_id"), F.col("col_id").cast("bigint").alias("col"), r6(F.col("v"), "v"))


@q("SELECT s_name AS value FROM supplier")
def io_roundtrip_text(s: SparkSession, d: str) -> DataFrame:
    path = f"{S.root_of(s)}/text"
    T.load(s, d, "supplier").select(F.col("s_name").alias("value")).write.text(path)
    return s.read.text(path)


@q(f"SELECT CAST(r AS BIGINT) AS row_id, CAST(c AS BIGINT) AS col, round({gaussian_sql(7, 'r', 'c')}, 6) + 0.0 AS g FROM (SELECT unnest(range(2000)) AS r), (SELECT unnest(range(16)) AS c)")
def src_random_matrix(s: SparkSession, d: str) -> DataFrame:
    """Random rows by key, never stored."""

    def run(batches):
        for b in batches:
            x = gaussians(7, b.column(0).to_pylist(), 16)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(x.tolist(), pa.list_(pa.float64()))], names=["row_id", "x"])

    rows = s.range(2000).withColumnRenamed("id", "row_id").mapInArrow(run, "row_id bigint, x array<double>")
    return T.entries(rows).select("row_id", F.col("col_id").cast("bigint").alias("col"), r6(F.col("v"), "g"))
