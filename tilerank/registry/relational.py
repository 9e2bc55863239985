"""Sources, matrix builders, products, joins, aggregates, windows, sets and scalar functions on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tilerank.functions import vectors as V
from tilerank.functions.keyed import gaussian, gaussian_sql
from tilerank.operators.matrix import Tall, with_index
from tilerank.operators.tiles import combine, multiply_thin, trailing
from tilerank.sources import tables as T

from . import sqlgen as G

QUERIES: dict = {}
ORACLES: dict = {}


def q(oracle: str | None = None):
    def put(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return put


def r6(c, name: str):
    return (F.round(c, 6) + 0.0).alias(name)


def emb(s: SparkSession, d: str) -> DataFrame:
    """Entries (row_id, col_id, v) of the embedding matrix."""
    return T.entries(T.emb(s, d))


E, LI = G.EMB, "lineitem"
BIG = "CAST({} AS BIGINT)".format


# sources and builders


@q(" UNION ALL ".join(f"SELECT '{t}' AS table_name, count(*) AS n FROM {t}" for t in T.TABLES))
def src_table_counts(s: SparkSession, d: str) -> DataFrame:
    out = None
    for t in T.TABLES:
        one = T.load(s, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("table_name"), "n")
        out = one if out is None else out.union(one)
    return out


@q(f"SELECT o_orderkey AS row_id, CAST(c AS BIGINT) AS col, round({gaussian_sql(3, 'o_orderkey', 'c')}, 6) + 0.0 AS g FROM orders, (SELECT unnest(range(4)) AS c)")
def src_keyed_gaussian(s: SparkSession, d: str) -> DataFrame:
    o = T.load(s, d, "orders").select(F.col("o_orderkey").alias("row_id"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(3).cast("bigint"))).alias("col"))
    return o.select("row_id", "col", r6(gaussian(3, F.col("row_id"), F.col("col")), "g"))


EMB_ENTRIES = f"SELECT row_id AS vec_id, {BIG('col_id')} AS col, round(v, 6) + 0.0 AS v FROM ({E})"


@q(EMB_ENTRIES)
def mat_emb_entries(s: SparkSession, d: str) -> DataFrame:
    return emb(s, d).select(F.col("row_id").alias("vec_id"), F.col("col_id").cast("bigint").alias("col"), r6(F.col("v"), "v"))


LINE_MD5 = "md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber))"


@q(" UNION ALL ".join(f"SELECT {LINE_MD5} AS k, '{c}' AS name, CAST({c} AS DOUBLE) AS v FROM lineitem" for c in T.LINE4))
def mat_line_unpivot(s: SparkSession, d: str) -> DataFrame:
    li = T.load(s, d, LI).select(F.md5(F.concat_ws("|", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")).alias("k"), *T.LINE4)
    return li.unpivot("k", list(T.LINE4), "name", "v")


DESIGN = ["1.0", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_extendedprice * (1 - l_discount)", "l_extendedprice * l_discount", *[f"CAST(l_returnflag = '{x}' AS DOUBLE)" for x in "ANR"], *[f"CAST(l_linestatus = '{x}' AS DOUBLE)" for x in "OF"]]


@q(" UNION ALL ".join(f"SELECT {BIG(i)} AS col, round(sqrt(sum(({c}) * ({c}))), 3) + 0.0 AS norm FROM lineitem" for i, c in enumerate(DESIGN)))
def mat_design_colnorms(s: SparkSession, d: str) -> DataFrame:
    sums = T.load(s, d, LI).select(*[c.alias(f"c{i}") for i, c in enumerate(T.design_columns())]).agg(*[F.sqrt(F.sum(F.col(f"c{i}") ** 2)).alias(f"c{i}") for i in range(12)])
    return sums.select(F.posexplode(F.array(*[f"c{i}" for i in range(12)])).alias("col", "norm")).select(F.col("col").cast("bigint").alias("col"), (F.round("norm", 3) + 0.0).alias("norm"))


@q("SELECT user_id, " + ", ".join(f"round(coalesce(sum(value) FILTER (hour(ts) = {h}), 0), 6) + 0.0 AS h{h}" for h in range(24)) + " FROM events GROUP BY 1")
def mat_userhour_pivot(s: SparkSession, d: str) -> DataFrame:
    p = T.load(s, d, "events").withColumn("h", F.hour("ts")).groupBy("user_id").pivot("h", list(range(24))).agg(F.sum("value"))
    return p.select("user_id", *[r6(F.coalesce(F.col(f"`{h}`"), F.lit(0.0)), f"h{h}") for h in range(24)])


@q("SELECT l_suppkey, " + ", ".join(f"coalesce(sum(l_quantity) FILTER (month(l_shipdate) = {m}), 0) + 0.0 AS m{m}" for m in range(1, 13)) + " FROM lineitem WHERE year(l_shipdate) = 1995 GROUP BY 1")
def mat_suppmonth_pivot(s: SparkSession, d: str) -> DataFrame:
    li = T.load(s, d, LI).where((F.col("l_shipdate") >= "1995-01-01") & (F.col("l_shipdate") < "1996-01-01"))
    p = li.withColumn("m", F.month("l_shipdate")).groupBy("l_suppkey").pivot("m", list(range(1, 13))).agg(F.sum("l_quantity"))
    return p.select("l_suppkey", *[F.coalesce(F.col(f"`{m}`"), F.lit(0.0)).alias(f"m{m}") for m in range(1, 13)])


TILES = f"SELECT {BIG('row_id // 24')} AS bi, {BIG('col_id // 24')} AS bj, count(*) AS nnz, sum(v) + 0.0 AS tile_sum FROM ({G.SUPPPART}) GROUP BY 1, 2"


@q(TILES)
def mat_supppart_tiles(s: SparkSession, d: str) -> DataFrame:
    e = T.supppart(s, d)
    return e.groupBy(F.floor(F.col("row_id") / 24).alias("bi"), F.floor(F.col("col_id") / 24).alias("bj")).agg(F.count("*").alias("nnz"), F.sum("v").alias("tile_sum"))


@q("SELECT doc_id, CAST('0x' || substr(md5(w), 1, 8) AS BIGINT) % 256 AS bucket, count(*) AS tf FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '[ \\n\\t\\r]+')) AS w FROM documents) WHERE w <> '' GROUP BY 1, 2")
def mat_term_counts(s: SparkSession, d: str) -> DataFrame:
    w = T.load(s, d, "documents").select("doc_id", F.explode(F.split(F.lower("text"), "[ \\n\\t\\r]+")).alias("w")).where("w <> ''")
    return w.groupBy("doc_id", (F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("bigint") % 256).alias("bucket")).agg(F.count("*").alias("tf"))


TAGS = "SELECT page_id, tag, count(*) AS n FROM (SELECT page_id, unnest(regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1)) AS tag FROM pages) GROUP BY 1, 2"


@q(TAGS)
def mat_page_tags(s: SparkSession, d: str) -> DataFrame:
    return T.load(s, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit("<([a-z][a-z0-9]*)"), F.lit(1))).alias("tag")).groupBy("page_id", "tag").agg(F.count("*").alias("n"))


@q("SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS text_chars, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title FROM pages WHERE html IS NOT NULL")
def fn_html_tags(s: SparkSession, d: str) -> DataFrame:
    """Markup taken out, and a tag's content."""
    p = T.load(s, d, "pages").where("html is not null")
    return p.select("page_id", F.char_length(F.regexp_replace("html", "<[^>]*>", "")).cast("bigint").alias("text_chars"), F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"))


@q(" UNION ALL ".join(f"SELECT '{c}' AS col, round(avg({c}), 4) + 0.0 AS mean, round(stddev_pop({c}), 4) + 0.0 AS sd, round((min({c}) - avg({c})) / stddev_pop({c}), 5) + 0.0 AS min_z, round((max({c}) - avg({c})) / stddev_pop({c}), 5) + 0.0 AS max_z FROM lineitem" for c in T.LINE4))
def mat_standardize(s: SparkSession, d: str) -> DataFrame:
    long = T.load(s, d, LI).select(*T.LINE4).unpivot([], list(T.LINE4), "col", "v")
    a = long.groupBy("col").agg(F.avg("v").alias("m"), F.stddev_pop("v").alias("s"), F.min("v").alias("lo"), F.max("v").alias("hi"))
    return a.select("col", (F.round("m", 4) + 0.0).alias("mean"), (F.round("s", 4) + 0.0).alias("sd"), (F.round((F.col("lo") - F.col("m")) / F.col("s"), 5) + 0.0).alias("min_z"), (F.round((F.col("hi") - F.col("m")) / F.col("s"), 5) + 0.0).alias("max_z"))


@q(EMB_ENTRIES)
def mat_transpose_roundtrip(s: SparkSession, d: str) -> DataFrame:
    m = T.load(s, d, "embeddings").count()
    back = T.transpose_tiles(T.transpose_tiles(T.to_tiles(emb(s, d), 24, 64, m)))
    return T.from_tiles(back, 24).select(F.col("row_id").alias("vec_id"), F.col("col_id").cast("bigint").alias("col"), r6(F.col("v"), "v"))


@q(EMB_ENTRIES)
def mat_tile_roundtrip(s: SparkSession, d: str) -> DataFrame:
    m = T.load(s, d, "embeddings").count()
    return T.from_tiles(T.to_tiles(emb(s, d), 40, 64, m), 40).select(F.col("row_id").alias("vec_id"), F.col("col_id").cast("bigint").alias("col"), r6(F.col("v"), "v"))


# products


def gram_entries(e: DataFrame) -> DataFrame:
    a, b = e.select("row_id", F.col("col_id").alias("i"), F.col("v").alias("x")), e.select("row_id", F.col("col_id").alias("j"), F.col("v").alias("y"))
    return a.join(b, "row_id").groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("g"))


def ij(df: DataFrame) -> DataFrame:
    return df.select(F.col("i").cast("bigint").alias("i"), F.col("j").cast("bigint").alias("j"), r6(F.col("g"), "g"))


GRAM = f"WITH {G.gram(E)} SELECT {BIG('i')} AS i, {BIG('j')} AS j, round(v, 6) + 0.0 AS g FROM g0"


@q(GRAM)
def lin_gram_emb(s: SparkSession, d: str) -> DataFrame:
    g = Tall(T.emb(s, d)).gram()
    return ij(s.createDataFrame([(i, j, float(g[i, j])) for i in range(64) for j in range(64)], "i int, j int, g double"))


@q(f"WITH {G.gram(E)} SELECT e.row_id AS vec_id, {BIG('g0.j')} AS col, round(sum(e.v * g0.v), 6) + 0.0 AS v FROM e JOIN g0 ON e.col_id = g0.i GROUP BY 1, 2")
def lin_matmul_entries(s: SparkSession, d: str) -> DataFrame:
    """A (A'A) by entries; the Gram matrix comes from a pass over the rows, and is broadcast if its n x n entries are few."""
    e, g = emb(s, d), Tall(T.emb(s, d)).gram()
    n = len(g)
    g = s.createDataFrame([(i, j, float(g[i, j])) for i in range(n) for j in range(n)], "i int, j int, g double")
    return e.join(F.broadcast(g) if 16 * n * n <= 8 << 20 else g, e["col_id"] == g["i"]).groupBy(F.col("row_id").alias("vec_id"), F.col("j").cast("bigint").alias("col")).agg(r6(F.sum(F.col("v") * F.col("g")), "v"))


@q(f"WITH e AS ({G.SUPPPART}) SELECT a.row_id, {BIG('b.row_id')} AS col, sum(a.v * b.v) + 0.0 AS v FROM e a JOIN e b ON a.col_id = b.col_id GROUP BY 1, 2")
def lin_tile_matmul(s: SparkSession, d: str) -> DataFrame:
    """A A' by tiles: 64 columns are few, so a square of the result is made in one task and no product is shuffled."""
    m = T.load(s, d, "supplier").count()
    t, p = T.to_tiles(T.supppart(s, d), 16, 64, m), -(-m // 16)
    return T.from_tiles(multiply_thin(t, T.transpose_tiles(t), p, p), 16).where("v <> 0").select("row_id", F.col("col_id").cast("bigint").alias("col"), "v")


TILE_COMBINE = f"""WITH e AS ({G.SUPPPART}), h AS (SELECT l_suppkey AS row_id, l_partkey % 64 AS col_id, sum(l_quantity) AS v FROM lineitem WHERE l_returnflag = 'R' GROUP BY 1, 2)
SELECT {BIG('e.row_id')} AS row_id, {BIG('e.col_id')} AS col, e.v - 2 * coalesce(h.v, 0) + 0.0 AS axpy, e.v * coalesce(h.v, 0) + 0.0 AS hadamard FROM e LEFT JOIN h USING (row_id, col_id)"""


@q(TILE_COMBINE)
def lin_tile_combine(s: SparkSession, d: str) -> DataFrame:
    """Y - 2 X and the entrywise product of two tile frames, where X lacks tiles."""
    m = T.load(s, d, "supplier").count()
    li = T.load(s, d, LI).where("l_returnflag = 'R'")
    part = li.groupBy(F.col("l_suppkey").alias("row_id"), F.pmod("l_partkey", F.lit(64)).cast("int").alias("col_id")).agg(F.sum("l_quantity").alias("v"))
    y, x = (T.to_tiles(e, 16, 64, m) for e in (T.supppart(s, d), part))
    made = [T.from_tiles(combine(y, x, f), 16).withColumnRenamed("v", name) for f, name in ((lambda a, b: a - 2 * b, "axpy"), (lambda a, b: a * b, "hadamard"))]
    there = T.supppart(s, d).select("row_id", "col_id")
    return there.join(made[0], ["row_id", "col_id"]).join(made[1], ["row_id", "col_id"]).select("row_id", F.col("col_id").cast("bigint").alias("col"), F.col("axpy") + 0.0, F.col("hadamard") + 0.0).toDF("row_id", "col", "axpy", "hadamard")


@q(f"SELECT {BIG('row_id // 24')} AS bi, {BIG('col_id // 24')} AS bj, sum(v) + 0.0 AS s FROM ({G.SUPPPART}) WHERE row_id // 24 >= 1 AND col_id // 24 >= 1 GROUP BY 1, 2")
def mat_trailing_tiles(s: SparkSession, d: str) -> DataFrame:
    """The trailing block of the tile grid."""
    m = T.load(s, d, "supplier").count()
    t = trailing(T.to_tiles(T.supppart(s, d), 24, 64, m), 1)
    return t.groupBy(F.col("bi").cast("bigint").alias("bi"), F.col("bj").cast("bigint").alias("bj")).agg(V.tile_sum("data").alias("s"))


@q(f"WITH e AS ({E}), n AS (SELECT {BIG('row_id')} AS row_id, v, col_id, row_number() OVER (PARTITION BY col_id ORDER BY row_id) - 1 AS p FROM e) SELECT {BIG('p // 128')} AS slab, count(DISTINCT row_id) AS rows, round(sum(v * v), 6) + 0.0 AS energy FROM n GROUP BY 1")
def mat_row_slabs(s: SparkSession, d: str) -> DataFrame:
    """Rows in slabs of 128 by row id."""
    slabs = T.to_slabs(T.emb(s, d), 128)
    energy = F.aggregate("x", F.lit(0.0), lambda t, v: t + v * v)
    return slabs.groupBy("slab").agg(F.count_distinct("row_id").alias("rows"), r6(F.sum(energy), "energy"))


@q(f"WITH a AS (SELECT col_id, avg(v) AS m, sqrt(avg(v * v) - avg(v) * avg(v)) AS s FROM ({E}) GROUP BY 1) SELECT row_id AS vec_id, {BIG('col_id')} AS col, round((v - m) / s, 5) + 0.0 AS z FROM ({E}) JOIN a USING (col_id)")
def mat_scaled(s: SparkSession, d: str) -> DataFrame:
    """Columns centred and scaled to unit variance."""
    z = T.scaled(T.emb(s, d), 64)
    return T.entries(z).select(F.col("row_id").alias("vec_id"), F.col("col_id").cast("bigint").alias("col"), (F.round("v", 5) + 0.0).alias("z"))


@q(f"SELECT row_id AS vec_id, {BIG('63 - col_id')} AS col, round(v, 6) + 0.0 AS v FROM ({E}) WHERE col_id % 2 = 1")
def mat_select_permute(s: SparkSession, d: str) -> DataFrame:
    """Odd columns only, in reverse: a selection and a permutation of columns; each is put at its place of the reversed matrix."""
    odd = T.select_columns(T.emb(s, d), list(range(63, 0, -2)))
    return T.entries(odd).select(F.col("row_id").alias("vec_id"), (2 * F.col("col_id")).cast("bigint").alias("col"), r6(F.col("v"), "v"))


FROB = {"emb": E, "userhour": G.USERHOUR, "suppmonth": G.SUPPMONTH, "supppart": G.SUPPPART}


@q(" UNION ALL ".join(f"SELECT '{k}' AS matrix, round(sqrt(sum(v * v)), 4) + 0.0 AS frob FROM ({e})" for k, e in FROB.items()))
def lin_frob_norms(s: SparkSession, d: str) -> DataFrame:
    e = {"emb": emb(s, d), "userhour": T.entries(T.userhour(s, d)), "suppmonth": T.entries(T.suppmonth(s, d)), "supppart": T.supppart(s, d)}
    out = None
    for k, df in e.items():
        one = df.agg((F.round(F.sqrt(F.sum(F.col("v") ** 2)), 4) + 0.0).alias("frob")).select(F.lit(k).alias("matrix"), "frob")
        out = one if out is None else out.union(one)
    return out


# joins


@q(f"WITH e AS ({G.SUPPPART}) SELECT {BIG('a.col_id')} AS i, {BIG('b.col_id')} AS j, sum(a.v * b.v) + 0.0 AS v FROM e a JOIN e b USING (row_id) GROUP BY 1, 2")
def join_contract(s: SparkSession, d: str) -> DataFrame:
    return gram_entries(T.supppart(s, d)).select(F.col("i").cast("bigint").alias("i"), F.col("j").cast("bigint").alias("j"), F.col("g").alias("v"))


def weighted(s: SparkSession, d: str, how) -> DataFrame:
    w = s.range(64).select(F.col("id").cast("int").alias("col_id"), (1.0 / (F.col("id") + 1)).alias("w"))
    return emb(s, d).join(how(w), "col_id").groupBy(F.col("row_id").alias("vec_id")).agg(r6(F.sum(F.col("v") * F.col("w")), "y"))


WEIGHTED = f"SELECT row_id AS vec_id, round(sum(v / (col_id + 1.0)), 6) + 0.0 AS y FROM ({E}) GROUP BY 1"


@q(WEIGHTED)
def join_broadcast_thin(s: SparkSession, d: str) -> DataFrame:
    return weighted(s, d, F.broadcast)


@q(WEIGHTED)
def join_shuffle_hash(s: SparkSession, d: str) -> DataFrame:
    return weighted(s, d, lambda w: w.hint("shuffle_hash"))


@q(f"WITH t AS ({TILES}), g AS (SELECT unnest(range((SELECT max(l_suppkey) // 24 + 1 FROM lineitem))) AS bi), h AS (SELECT unnest(range(3)) AS bj) SELECT {BIG('g.bi')} AS bi, {BIG('h.bj')} AS bj, t.nnz IS NOT NULL AS present FROM g CROSS JOIN h LEFT JOIN t ON t.bi = g.bi AND t.bj = h.bj")
def join_cross_grid(s: SparkSession, d: str) -> DataFrame:
    """Every place of the tile grid, with or without a tile: tile rows by the three tile columns."""
    rows = T.load(s, d, LI).agg(F.max("l_suppkey")).first()[0] // 24 + 1
    grid = s.range(rows).select(F.col("id").alias("bi"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(2).cast("bigint"))).alias("bj"))
    return grid.join(mat_supppart_tiles(s, d), ["bi", "bj"], "left").select("bi", "bj", F.col("nnz").isNotNull().alias("present"))


@q(f"WITH e AS ({E}) SELECT {BIG('a.col_id')} AS i, {BIG('b.col_id')} AS j, round(sum(a.v * b.v), 6) + 0.0 AS g FROM e a JOIN e b ON a.row_id = b.row_id AND a.col_id <= b.col_id GROUP BY 1, 2")
def join_theta_upper(s: SparkSession, d: str) -> DataFrame:
    e = emb(s, d)
    a, b = e.select("row_id", F.col("col_id").alias("i"), F.col("v").alias("x")), e.select(F.col("row_id").alias("r"), F.col("col_id").alias("j"), F.col("v").alias("y"))
    return ij(a.join(b, (F.col("row_id") == F.col("r")) & (F.col("i") <= F.col("j"))).groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("g")))


@q(f"SELECT {BIG('col_id')} AS col, {BIG('col_id // 24')} AS panel, {BIG('least(24, 64 - col_id // 24 * 24)')} AS width, count(*) AS n, round(sum(v * v), 6) + 0.0 AS energy FROM ({E}) GROUP BY 1, 2, 3")
def join_range_panels(s: SparkSession, d: str) -> DataFrame:
    """Interval join by bins of the embeddings' columns with panels of them: a panel is listed under each bin of 16 columns that it touches."""
    panels = s.createDataFrame([(i, 24 * i, min(64, 24 * i + 24)) for i in range(3)], "panel bigint, lo bigint, hi bigint")
    binned = panels.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / 16), F.floor((F.col("hi") - 1) / 16))))
    cols = emb(s, d).groupBy(F.col("col_id").cast("bigint").alias("col")).agg(F.count("*").alias("n"), F.sum(F.col("v") * F.col("v")).alias("e")).withColumn("bin", F.floor(F.col("col") / 16))
    return cols.join(F.broadcast(binned), "bin").where("col >= lo and col < hi").select("col", "panel", (F.col("hi") - F.col("lo")).alias("width"), "n", r6(F.col("e"), "energy"))


ASOF = """SELECT p.event_id, v.event_id AS prev_event_id, CAST(date_diff('second', v.ts, p.ts) AS BIGINT) AS gap_seconds
FROM (SELECT * FROM events WHERE event_type = '{a}') p ASOF JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = '{b}' GROUP BY 1, 2) v ON p.user_id = v.user_id AND p.ts > v.ts"""


@q(ASOF.format(a="purchase", b="view"))
def join_asof_events(s: SparkSession, d: str) -> DataFrame:
    """Each purchase with the user's latest earlier view: one window by user, no pairs. Views of one instant: the largest id."""
    e = T.load(s, d, "events").where("event_type in ('purchase', 'view')")
    view = F.when(F.col("event_type") == "view", F.struct("ts", "event_id"))
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(Window.unboundedPreceding, -1)
    e = e.withColumn("v", F.max(view).over(w))
    gap = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000) - F.floor(F.unix_micros(F.col("v.ts").cast("timestamp")) / 1_000_000)
    return e.where("event_type = 'purchase' and v is not null").select("event_id", F.col("v.event_id").alias("prev_event_id"), gap.cast("bigint").alias("gap_seconds"))


FLAG_TILES = "SELECT l_suppkey // 24 AS bi, l_partkey % 64 // 24 AS bj, sum(l_quantity) AS v FROM lineitem WHERE l_returnflag = '{}' GROUP BY 1, 2"


@q(f"SELECT {BIG('coalesce(a.bi, r.bi)')} AS bi, {BIG('coalesce(a.bj, r.bj)')} AS bj, coalesce(a.v, 0) - coalesce(r.v, 0) + 0.0 AS diff FROM ({FLAG_TILES.format('A')}) a FULL JOIN ({FLAG_TILES.format('R')}) r ON a.bi = r.bi AND a.bj = r.bj")
def join_outer_missing_tiles(s: SparkSession, d: str) -> DataFrame:
    def tiles(flag: str, name: str) -> DataFrame:
        li = T.load(s, d, LI).where(F.col("l_returnflag") == flag)
        return li.groupBy(F.floor(F.col("l_suppkey") / 24).alias("bi"), F.floor(F.col("l_partkey") % 64 / 24).alias("bj")).agg(F.sum("l_quantity").alias(name))

    return tiles("A", "a").join(tiles("R", "r"), ["bi", "bj"], "full").select("bi", "bj", (F.coalesce("a", F.lit(0.0)) - F.coalesce("r", F.lit(0.0))).alias("diff"))


@q(f"WITH {G.classical(E, 8)}, chosen AS ({' UNION ALL '.join(f'SELECT p FROM p{t}' for t in range(8))}) SELECT row_id AS vec_id, {BIG('col_id')} AS col, round(v, 6) + 0.0 AS v FROM e WHERE col_id IN (SELECT p FROM chosen)")
def join_semi_selected(s: SparkSession, d: str) -> DataFrame:
    from tilerank.operators.apps import select_columns

    chosen = s.createDataFrame([(int(c),) for c in select_columns(Tall(T.emb(s, d)), 8)], "col_id int")
    return emb(s, d).join(F.broadcast(chosen), "col_id", "left_semi").select(F.col("row_id").alias("vec_id"), F.col("col_id").cast("bigint").alias("col"), r6(F.col("v"), "v"))


@q("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti_unlabelled(s: SparkSession, d: str) -> DataFrame:
    return T.load(s, d, "documents").select("doc_id").join(T.load(s, d, "labels").select("doc_id"), "doc_id", "left_anti")


@q(f"WITH {G.gram(E)} SELECT {BIG('g.i')} AS i, {BIG('g.j')} AS j, round(g.v / sqrt(a.v * b.v), 6) + 0.0 AS cos FROM g0 g JOIN g0 a ON a.i = g.i AND a.j = g.i JOIN g0 b ON b.i = g.j AND b.j = g.j WHERE g.i < g.j AND g.v / sqrt(a.v * b.v) >= 0.1")
def join_self_gram(s: SparkSession, d: str) -> DataFrame:
    g = gram_entries(emb(s, d))
    n = g.where("i = j").select(F.col("i").alias("c"), F.sqrt("g").alias("n"))
    c = g.join(F.broadcast(n.toDF("i", "ni")), "i").join(F.broadcast(n.toDF("j", "nj")), "j").withColumn("cos", F.col("g") / (F.col("ni") * F.col("nj")))
    return c.where("i < j and cos >= 0.1").select(F.col("i").cast("bigint").alias("i"), F.col("j").cast("bigint").alias("j"), r6(F.col("cos"), "cos"))


@q("SELECT n_name, c_custkey, c_acctbal FROM (SELECT n_name, c_custkey, c_acctbal, row_number() OVER (PARTITION BY n_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn FROM nation JOIN customer ON c_nationkey = n_nationkey) WHERE rn <= 3")
def join_lateral(s: SparkSession, d: str) -> DataFrame:
    """Top three by nation: a lateral subquery for each nation, which Catalyst turns into one ranked join."""
    T.load(s, d, "nation").createOrReplaceTempView("nations__")
    T.load(s, d, "customer").createOrReplaceTempView("customers__")
    return s.sql("SELECT n_name, t.c_custkey, t.c_acctbal FROM nations__, LATERAL (SELECT c_custkey, c_acctbal FROM customers__ WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3) t")


@q("SELECT l_returnflag AS flag, sum(l_quantity * w) + 0.0 AS qty FROM lineitem JOIN (SELECT l_returnflag AS f, CAST(count(DISTINCT l_linestatus) AS DOUBLE) AS w FROM lineitem GROUP BY 1) ON f = l_returnflag GROUP BY 1")
def join_salted(s: SparkSession, d: str) -> DataFrame:
    """A join on few hot keys: the other side comes once for each salt, the hot rows are dealt out by it, and sums are taken in two steps."""
    li = T.load(s, d, LI)
    weights = li.groupBy(F.col("l_returnflag").alias("flag")).agg(F.count_distinct("l_linestatus").cast("double").alias("w"))
    weights = weights.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(15))))
    dealt = li.select(F.col("l_returnflag").alias("flag"), "l_quantity", F.pmod(F.xxhash64("l_orderkey", "l_partkey"), F.lit(16)).cast("int").alias("salt"))
    joined = dealt.join(weights.hint("merge"), ["flag", "salt"])
    return joined.groupBy("flag", "salt").agg(F.sum(F.col("l_quantity") * F.col("w")).alias("q")).groupBy("flag").agg(F.sum("q").alias("qty"))


@q(f"WITH e AS ({G.SUPPPART}), t AS (SELECT row_id // 24 AS r, col_id // 24 AS j, count(DISTINCT row_id) AS nr, sum(v * v) AS energy FROM e GROUP BY 1, 2) SELECT {BIG('b.r')} AS r, {BIG('b.j')} AS j, {BIG('a.nr + b.nr')} AS nr, a.energy + b.energy + 0.0 AS energy FROM t a JOIN t b ON a.j = b.j AND a.r = 0 AND b.r > 0")
def join_cogroup_pair(s: SparkSession, d: str) -> DataFrame:
    """Tile pairs (0, j) and (r, j) brought to one task."""
    import numpy as np
    import pyarrow as pa

    m = T.load(s, d, "supplier").count()
    t, again = (T.to_tiles(T.supppart(s, d), 24, 64, m) for _ in range(2))  # two readings: one frame can't be cogrouped with itself
    below = s.range(1, -(-m // 24)).select(F.col("id").cast("int").alias("bi"))
    heads = t.where("bi = 0").drop("bi").crossJoin(F.broadcast(below))

    def pair(left: pa.Table, right: pa.Table) -> pa.Table:
        rows = [(b["bi"], b["bj"], a["nr"] + b["nr"], float((np.frombuffer(a["data"]) ** 2).sum() + (np.frombuffer(b["data"]) ** 2).sum())) for a in left.to_pylist() for b in right.to_pylist()]
        return pa.table([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.float64()))] if rows else [pa.array([], x) for x in (pa.int64(), pa.int64(), pa.int64(), pa.float64())], names=["r", "j", "nr", "energy"])

    return heads.groupBy("bi", "bj").cogroup(again.where("bi > 0").groupBy("bi", "bj")).applyInArrow(pair, "r bigint, j bigint, nr bigint, energy double")


@q("SELECT r_name, CAST(year(o_orderdate) AS INTEGER) AS y, round(sum(l_extendedprice * (1 - l_discount)) / 1000, 3) + 0.0 AS rev FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def join_multi_star(s: SparkSession, d: str) -> DataFrame:
    li = T.load(s, d, LI).select("l_orderkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("x"))
    per_order = li.groupBy("l_orderkey").agg(F.sum("x").alias("x"))  # before the joins: fewer rows to move
    o = T.load(s, d, "orders").select("o_orderkey", "o_custkey", F.year("o_orderdate").alias("y"))
    c = T.load(s, d, "customer").select("c_custkey", "c_nationkey")
    n = T.load(s, d, "nation").join(T.load(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    j = per_order.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.groupBy("r_name", "y").agg((F.round(F.sum("x") / 1000, 3) + 0.0).alias("rev"))


# aggregates


@q("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) + 0.0 AS s, round(avg(l_extendedprice), 4) + 0.0 AS a, min(l_discount) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY 1, 2")
def agg_basic(s: SparkSession, d: str) -> DataFrame:
    return T.load(s, d, LI).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), (F.round(F.sum("l_quantity"), 2) + 0.0).alias("s"), (F.round(F.avg("l_extendedprice"), 4) + 0.0).alias("a"), F.min("l_discount").alias("lo"), F.max("l_tax").alias("hi"))


NORMS = f"SELECT col_id AS col, sqrt(sum(v * v)) AS norm FROM ({E}) GROUP BY 1"


def norms(s: SparkSession, d: str) -> DataFrame:
    return emb(s, d).groupBy(F.col("col_id").cast("bigint").alias("col")).agg(F.sqrt(F.sum(F.col("v") ** 2)).alias("norm"))


@q(f"SELECT {BIG('col')} AS pivot_col, round(norm, 6) + 0.0 AS norm FROM ({NORMS}) ORDER BY norm DESC, col LIMIT 1")
def agg_first_pivot(s: SparkSession, d: str) -> DataFrame:
    return norms(s, d).agg(F.max_by("col", F.struct("norm", -F.col("col"))).alias("pivot_col"), r6(F.max("norm"), "norm"))


@q(f"WITH {G.gram(G.LINE4)} SELECT {BIG('i')} AS i, {BIG('j')} AS j, round(v / (SELECT count(*) FROM lineitem) / 1000, 3) + 0.0 AS g FROM g0")
def agg_gram(s: SparkSession, d: str) -> DataFrame:
    cols = [F.col(c) for c in T.LINE4]
    sums = T.load(s, d, LI).agg(F.array(*[F.avg(a * b) for a in cols for b in cols]).alias("g"))
    e = sums.select(F.posexplode("g").alias("p", "g"))
    return e.select(F.floor(F.col("p") / 4).alias("i"), (F.col("p") % 4).cast("bigint").alias("j"), (F.round(F.col("g") / 1000, 3) + 0.0).alias("g"))


@q(f"SELECT CAST(s AS BIGINT) AS s, {BIG('col_id')} AS col, round(sum(v * {gaussian_sql(5, 'row_id', 's')}), 4) + 0.0 AS y FROM ({G.USERHOUR}), (SELECT unnest(range(4)) AS s) GROUP BY 1, 2")
def agg_sketch(s: SparkSession, d: str) -> DataFrame:
    """The Gaussian sketch as an aggregate: keys only, no draw is stored."""
    e = T.entries(T.userhour(s, d)).where("v <> 0")
    g = e.select("row_id").distinct().select("row_id", F.explode(F.sequence(F.lit(0), F.lit(3))).alias("s")).withColumn("g", gaussian(5, F.col("row_id"), F.col("s")))
    return e.join(g, "row_id").groupBy(F.col("s").cast("bigint").alias("s"), F.col("col_id").cast("bigint").alias("col")).agg((F.round(F.sum(F.col("v") * F.col("g")), 4) + 0.0).alias("y"))


@q("WITH t AS (SELECT l_suppkey // 24 AS bi, l_partkey % 64 // 24 AS bj, sum(l_quantity) AS v FROM lineitem GROUP BY 1, 2) SELECT CAST(bj AS BIGINT) AS bj, sum(v) + 0.0 AS v FROM t GROUP BY 1")
def agg_tile_sum(s: SparkSession, d: str) -> DataFrame:
    return mat_supppart_tiles(s, d).groupBy("bj").agg(F.sum("tile_sum").alias("v"))


@q(G.fixed_r(E, 64))
def agg_tree_r(s: SparkSession, d: str) -> DataFrame:
    """Triangles of seven leaves combined two by two."""
    from tilerank.functions import kernels as K

    from .methods import triangle_frame

    m = Tall(T.emb(s, d).repartition(7, "row_id"), 64)
    return triangle_frame(s, K.positive(m.reduce(lambda _, a: K.r_only(a), K.r_only, fan_in=2)))


@q("SELECT l_suppkey AS suppkey, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1")
def agg_distinct(s: SparkSession, d: str) -> DataFrame:
    return T.load(s, d, LI).groupBy(F.col("l_suppkey").alias("suppkey")).agg(F.count_distinct("l_partkey").alias("n"))


@q("SELECT l_returnflag, count(DISTINCT l_partkey) AS exact, TRUE AS near FROM lineitem GROUP BY 1")
def agg_approx_distinct(s: SparkSession, d: str) -> DataFrame:
    """The sketch's count lies within three of its standard errors of the exact one."""
    a = T.load(s, d, LI).groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("exact"), F.approx_count_distinct("l_partkey", 0.02).alias("approx"))
    return a.select("l_returnflag", "exact", (F.abs(F.col("approx") / F.col("exact") - 1) <= 0.06).alias("near"))


@q("SELECT l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 4) + 0.0 AS slope, round(regr_intercept(l_extendedprice, l_quantity), 3) + 0.0 AS icept, round(regr_r2(l_extendedprice, l_quantity), 6) + 0.0 AS r2, regr_count(l_extendedprice, l_quantity)::BIGINT AS n FROM lineitem GROUP BY 1")
def agg_regression(s: SparkSession, d: str) -> DataFrame:
    y, x = "l_extendedprice", "l_quantity"
    return T.load(s, d, LI).groupBy("l_returnflag").agg((F.round(F.regr_slope(y, x), 4) + 0.0).alias("slope"), (F.round(F.regr_intercept(y, x), 3) + 0.0).alias("icept"), r6(F.regr_r2(y, x), "r2"), F.regr_count(y, x).alias("n"))


REV = "round(sum(l_extendedprice), 2) + 0.0 AS rev"


@q(f"SELECT l_returnflag, l_linestatus, {REV} FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def agg_rollup(s: SparkSession, d: str) -> DataFrame:
    return T.load(s, d, LI).rollup("l_returnflag", "l_linestatus").agg((F.round(F.sum("l_extendedprice"), 2) + 0.0).alias("rev"))


@q(f"SELECT l_returnflag, l_linestatus, {REV} FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube(s: SparkSession, d: str) -> DataFrame:
    return T.load(s, d, LI).cube("l_returnflag", "l_linestatus").agg((F.round(F.sum("l_extendedprice"), 2) + 0.0).alias("rev"))


@q("SELECT event_type, " + ", ".join(f"round(quantile_cont(value, {p}), 6) + 0.0 AS p{int(100 * p)}" for p in (0.5, 0.9, 0.99)) + " FROM events GROUP BY 1")
def agg_percentile(s: SparkSession, d: str) -> DataFrame:
    return T.load(s, d, "events").groupBy("event_type").agg(*[r6(F.percentile("value", p), f"p{int(100 * p)}") for p in (0.5, 0.9, 0.99)])


@q(" UNION ALL ".join(f"SELECT '{a}' AS i, '{b}' AS j, round(corr({a}, {b}), 6) + 0.0 AS r FROM lineitem" for a in T.LINE4 for b in T.LINE4))
def agg_corr_matrix(s: SparkSession, d: str) -> DataFrame:
    one = T.load(s, d, LI).agg(F.array(*[F.struct(F.lit(a).alias("i"), F.lit(b).alias("j"), r6(F.corr(a, b), "r")) for a in T.LINE4 for b in T.LINE4]).alias("xs"))
    return one.select(F.inline("xs"))


@q("SELECT l_returnflag, round(stddev_samp(l_extendedprice), 3) + 0.0 AS sd, round(var_pop(l_quantity), 4) + 0.0 AS v, round(covar_samp(l_extendedprice, l_quantity), 2) + 0.0 AS c FROM lineitem GROUP BY 1")
def agg_variance_cov(s: SparkSession, d: str) -> DataFrame:
    return T.load(s, d, LI).groupBy("l_returnflag").agg((F.round(F.stddev_samp("l_extendedprice"), 3) + 0.0).alias("sd"), (F.round(F.var_pop("l_quantity"), 4) + 0.0).alias("v"), (F.round(F.covar_samp("l_extendedprice", "l_quantity"), 2) + 0.0).alias("c"))


@q("SELECT user_id, string_agg(h || ':' || n, ',' ORDER BY h) AS vec FROM (SELECT user_id, hour(ts) AS h, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1")
def agg_collect_row_vectors(s: SparkSession, d: str) -> DataFrame:
    c = T.load(s, d, "events").groupBy("user_id", F.hour("ts").alias("h")).agg(F.count("*").alias("n"))
    return c.groupBy("user_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("h", "n"))), lambda x: F.concat_ws(":", x["h"].cast("string"), x["n"].cast("string"))), ",").alias("vec"))


@q("SELECT user_id, count(*) FILTER (event_type = 'purchase') AS n FROM events GROUP BY 1 HAVING count(*) FILTER (event_type = 'purchase') >= 5")
def agg_filtered_having(s: SparkSession, d: str) -> DataFrame:
    return T.load(s, d, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "purchase").alias("n")).where("n >= 5")


@q("SELECT event_type, " + ", ".join(f"count(*) FILTER (hour(ts) = {h}) AS h{h}" for h in range(24)) + " FROM events GROUP BY 1")
def agg_pivot(s: SparkSession, d: str) -> DataFrame:
    p = T.load(s, d, "events").withColumn("h", F.hour("ts")).groupBy("event_type").pivot("h", list(range(24))).count()
    return p.select("event_type", *[F.coalesce(F.col(f"`{h}`"), F.lit(0)).cast("bigint").alias(f"h{h}") for h in range(24)])


# windows, sorts, sets


@q(f"SELECT {BIG('col')} AS col, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) + 0.0 AS pr, ntile(4) OVER w AS nt FROM ({NORMS}) WINDOW w AS (ORDER BY norm DESC, col)")
def win_rank_norms(s: SparkSession, d: str) -> DataFrame:
    """A row for each column: small, so one ordered window."""
    w = Window.orderBy(F.desc("norm"), "col")
    return norms(s, d).select("col", F.row_number().over(w).cast("bigint").alias("rn"), F.rank().over(w).cast("bigint").alias("rk"), F.dense_rank().over(w).cast("bigint").alias("dr"), r6(F.percent_rank().over(w), "pr"), F.ntile(4).over(w).cast("bigint").alias("nt"))


@q("SELECT event_id, row_number() OVER (ORDER BY event_id) - 1 AS idx FROM events")
def win_row_index(s: SparkSession, d: str) -> DataFrame:
    return with_index(T.load(s, d, "events").select("event_id"), "event_id", "idx")


def pivot_rows(s: SparkSession, d: str, k: int) -> DataFrame:
    from .methods import pivot_frame
    from tilerank.operators.sketchqr import pivoted_qr

    return pivot_frame(s, pivoted_qr(Tall(T.emb(s, d)), k))


@q(f"WITH {G.classical(E, 16)}, r AS ({G.pivots(16)}) SELECT k, round(sum(r_kk * r_kk) OVER (ORDER BY k), 4) + 0.0 AS cum FROM r")
def win_cum_energy(s: SparkSession, d: str) -> DataFrame:
    w = Window.orderBy("k").rowsBetween(Window.unboundedPreceding, 0)
    return pivot_rows(s, d, 16).select("k", (F.round(F.sum(F.col("r_kk") ** 2).over(w), 4) + 0.0).alias("cum"))


@q(f"WITH {G.classical(E, 16)}, r AS ({G.pivots(16)}) SELECT k, round(r_kk / lag(r_kk) OVER w, 5) + 0.0 AS ratio, lead(k) OVER w AS nxt, round(first_value(r_kk) OVER w, 5) + 0.0 AS top, round(nth_value(r_kk, 2) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), 5) + 0.0 AS second FROM r WINDOW w AS (ORDER BY k)")
def win_gap_lag(s: SparkSession, d: str) -> DataFrame:
    w = Window.orderBy("k")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    f5 = lambda c, n: (F.round(c, 5) + 0.0).alias(n)
    return pivot_rows(s, d, 16).select("k", f5(F.col("r_kk") / F.lag("r_kk").over(w), "ratio"), F.lead("k").over(w).alias("nxt"), f5(F.first("r_kk").over(w), "top"), f5(F.nth_value("r_kk", 2).over(whole), "second"))


@q("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 4) + 0.0 AS s FROM events")
def win_range_frame(s: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-3600, 0)
    e = T.load(s, d, "events").withColumn("sec", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000))
    return e.select("event_id", (F.round(F.sum("value").over(w), 4) + 0.0).alias("s"))


@q(f"SELECT {BIG('col_id')} AS col, row_id, v + 0.0 AS v FROM (SELECT *, row_number() OVER (PARTITION BY col_id ORDER BY v DESC, row_id) AS rn FROM ({G.SUPPMONTH})) WHERE rn <= 3")
def win_topk_per_group(s: SparkSession, d: str) -> DataFrame:
    e = T.entries(T.suppmonth(s, d))
    rn = F.row_number().over(Window.partitionBy("col_id").orderBy(F.desc("v"), "row_id"))
    return e.withColumn("rn", rn).where("rn <= 3").select(F.col("col_id").cast("bigint").alias("col"), "row_id", "v")


@q(f"SELECT {BIG('col')} AS col, round(norm, 6) + 0.0 AS norm FROM ({NORMS}) ORDER BY norm DESC, col LIMIT 10 OFFSET 5")
def sort_topk_columns(s: SparkSession, d: str) -> DataFrame:
    return norms(s, d).orderBy(F.desc("norm"), "col").offset(5).limit(10).select("col", r6(F.col("norm"), "norm"))


@q(f"SELECT row_id AS vec_id, round(sum(v * v), 6) + 0.0 AS e FROM ({E}) GROUP BY 1")
def set_union_stack(s: SparkSession, d: str) -> DataFrame:
    r = T.emb(s, d)
    both = r.where("row_id % 2 = 0").unionByName(r.where("row_id % 2 = 1").withColumn("half", F.lit(1)), allowMissingColumns=True)
    return both.select(F.col("row_id").alias("vec_id"), r6(V.vec_norm(F.col("x")) ** 2, "e"))


@q(f"SELECT \"pivot\" AS col FROM (WITH {G.classical(E, 16)} {G.pivots(16)}) INTERSECT SELECT \"pivot\" FROM ({G.sketched_pivots(E, 'SELECT vec_id AS row_id FROM embeddings', 16, 8, 7)})")
def set_intersect_pivots(s: SparkSession, d: str) -> DataFrame:
    from tilerank.operators.sketchqr import sketch_qr
    from .methods import pivot_frame

    a = pivot_rows(s, d, 16).select(F.col("pivot").alias("col"))
    return a.intersect(pivot_frame(s, sketch_qr(Tall(T.emb(s, d)), 8, 16, "triangle")).select(F.col("pivot").alias("col")))


BAG = "SELECT l_returnflag AS f, l_linestatus AS t, CAST(l_linenumber AS INTEGER) AS n FROM lineitem WHERE l_suppkey {}"


@q(f"SELECT 'both' AS side, f, t, n FROM ({BAG.format('% 2 = 0')} INTERSECT ALL {BAG.format('% 2 = 1')}) UNION ALL SELECT 'left', f, t, n FROM ({BAG.format('% 2 = 0')} EXCEPT ALL {BAG.format('% 2 = 1')})")
def set_intersect_except_all(s: SparkSession, d: str) -> DataFrame:
    li = T.load(s, d, LI)
    bag = lambda c: li.where(c).select(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("t"), F.col("l_linenumber").cast("int").alias("n"))
    a, b = bag("l_suppkey % 2 = 0"), bag("l_suppkey % 2 = 1")
    return a.intersectAll(b).select(F.lit("both").alias("side"), "*").union(a.exceptAll(b).select(F.lit("left").alias("side"), "*"))


# scalar functions

VEC = "list_transform(embedding, lambda x: CAST(x AS DOUBLE))"


@q(f"WITH v AS (SELECT vec_id, {VEC} AS x FROM embeddings) SELECT a.vec_id, round(list_dot_product(a.x, b.x), 6) + 0.0 AS dot, round(sqrt(list_sum(list_transform(list_zip(a.x, b.x), lambda p: (2 * p[1] + p[2]) * (2 * p[1] + p[2])))), 6) + 0.0 AS axpy_norm FROM v a JOIN v b ON b.vec_id = a.vec_id + 1")
def fn_vec_ops(s: SparkSession, d: str) -> DataFrame:
    a = T.emb(s, d)
    b = a.select((F.col("row_id") - 1).alias("row_id"), F.col("x").alias("y"))
    return a.join(b, "row_id").select(F.col("row_id").alias("vec_id"), r6(V.vec_dot(F.col("x"), F.col("y")), "dot"), r6(V.vec_norm(V.vec_axpy(F.lit(2.0), F.col("x"), F.col("y"))), "axpy_norm"))


@q(f"WITH v AS (SELECT vec_id, {VEC} AS x FROM embeddings), a AS (SELECT vec_id, x[1] AS f, CASE WHEN x[1] >= 0 THEN -1 ELSE 1 END * sqrt(list_dot_product(x, x)) AS alpha FROM v) SELECT vec_id, round(alpha, 6) + 0.0 AS alpha, round((alpha - f) / alpha, 6) + 0.0 AS beta FROM a")
def fn_householder(s: SparkSession, d: str) -> DataFrame:
    return T.emb(s, d).select(F.col("row_id").alias("vec_id"), V.house(F.col("x")).alias("h")).select("vec_id", r6(F.col("h.alpha"), "alpha"), r6(F.col("h.beta"), "beta"))


@q("SELECT doc_id, CAST(len(string_split(text, ' ')) AS BIGINT) AS n, CAST(list_max(list_transform(string_split(text, ' '), lambda x: length(x))) AS BIGINT) AS longest, substr(trim(text), 1, 8) AS head, CAST(levenshtein(lang, 'en') AS BIGINT) AS dist, concat_ws('_', 'A', lang, source) AS name FROM documents")
def fn_string_tokens(s: SparkSession, d: str) -> DataFrame:
    w = F.split("text", " ")
    return T.load(s, d, "documents").select("doc_id", F.size(w).cast("bigint").alias("n"), F.array_max(F.transform(w, lambda x: F.length(x))).cast("bigint").alias("longest"), F.substring(F.trim("text"), 1, 8).alias("head"), F.levenshtein("lang", F.lit("en")).cast("bigint").alias("dist"), F.concat_ws("_", F.lit("A"), "lang", "source").alias("name"))


@q("SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS mon, strftime(o_orderdate + INTERVAL 3 MONTH, '%Y-%m-%d') AS later FROM orders")
def fn_dates(s: SparkSession, d: str) -> DataFrame:
    o = F.col("o_orderdate")
    return T.load(s, d, "orders").select("o_orderkey", F.year(o).alias("y"), F.month(o).alias("m"), F.datediff(o, F.lit("1995-01-01")).alias("days"), F.date_format(F.date_trunc("month", o), "yyyy-MM-dd").alias("mon"), F.date_format(F.add_months(o, 3), "yyyy-MM-dd").alias("later"))


@q(f"WITH v AS (SELECT vec_id, {VEC} AS x FROM embeddings) SELECT vec_id, round(list_sum(list_slice(x, 3, 6)), 6) + 0.0 AS mid, round(list_sort(x)[1], 6) + 0.0 AS lo, CAST(list_position(x, list_max(x)) AS BIGINT) AS pos, CAST(len(flatten([x, list_slice(x, 1, 2)])) AS BIGINT) AS n, CAST(list_sum(range(vec_id, vec_id + 3)) AS BIGINT) AS seq FROM v")
def fn_array(s: SparkSession, d: str) -> DataFrame:
    x = F.col("x")
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda p, v: p + v)
    return T.emb(s, d).select(F.col("row_id").alias("vec_id"), r6(total(F.slice(x, 3, 4)), "mid"), r6(F.element_at(F.array_sort(x), 1), "lo"), F.array_position(x, F.array_max(x)).cast("bigint").alias("pos"), F.size(F.flatten(F.array(x, F.slice(x, 1, 2)))).cast("bigint").alias("n"), F.aggregate(F.sequence(F.col("row_id"), F.col("row_id") + 2), F.lit(0).cast("bigint"), lambda p, v: p + v).alias("seq"))


@q(f"SELECT 'c' || col AS key, round(norm, 6) + 0.0 AS value FROM ({NORMS})")
def fn_map_metrics(s: SparkSession, d: str) -> DataFrame:
    m = norms(s, d).agg(F.map_from_entries(F.collect_list(F.struct(F.concat(F.lit("c"), F.col("col").cast("string")), "norm"))).alias("m"))
    return m.select(F.explode(F.map_entries(F.transform_values("m", lambda k, v: F.round(v, 6) + 0.0))).alias("e")).select("e.key", "e.value")


@q("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def fn_variant_props(s: SparkSession, d: str) -> DataFrame:
    return T.load(s, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@q("SELECT o_orderkey, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) AS days, strftime(CAST(o_orderdate AS TIMESTAMP) + INTERVAL 1 MONTH + INTERVAL 36 HOUR, '%Y-%m-%d %H') AS later FROM orders")
def fn_intervals(s: SparkSession, d: str) -> DataFrame:
    o = T.load(s, d, "orders").withColumn("t", F.col("o_orderdate").cast("date").cast("timestamp"))
    later = F.col("t") + F.make_interval(F.lit(0), F.lit(1)) + F.make_interval(F.lit(0), F.lit(0), F.lit(0), F.lit(0), F.lit(36))
    return o.select("o_orderkey", F.timestamp_diff("DAY", F.lit("1992-01-01").cast("timestamp"), F.col("t")).cast("bigint").alias("days"), F.date_format(later, "yyyy-MM-dd HH").alias("later"))


@q("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json_props(s: SparkSession, d: str) -> DataFrame:
    p = F.from_json("props", "k bigint")
    return T.load(s, d, "events").select("event_id", F.get_json_object(F.to_json(p), "$.k").cast("bigint").alias("k"))


@q("SELECT c_custkey, round(ln(abs(c_acctbal) + 1), 6) + 0.0 AS l, round(exp(c_acctbal / 10000), 6) + 0.0 AS e, round(power(abs(c_acctbal), 0.5), 6) + 0.0 AS p, CAST(sign(c_acctbal) AS DOUBLE) AS s, CAST(floor(c_acctbal) AS BIGINT) AS f, CAST(ceil(c_acctbal) AS BIGINT) AS c, CAST(((c_custkey - 700) % 7 + 7) % 7 AS BIGINT) AS m, greatest(c_acctbal, 0) + 0.0 AS g FROM customer")
def fn_math(s: SparkSession, d: str) -> DataFrame:
    b = F.col("c_acctbal")
    return T.load(s, d, "customer").select("c_custkey", r6(F.log(F.abs(b) + 1), "l"), r6(F.exp(b / 10000), "e"), r6(F.pow(F.abs(b), F.lit(0.5)), "p"), F.signum(b).alias("s"), F.floor(b).cast("bigint").alias("f"), F.ceil(b).cast("bigint").alias("c"), F.pmod(F.col("c_custkey") - 700, F.lit(7)).cast("bigint").alias("m"), (F.greatest(b, F.lit(0.0)) + 0.0).alias("g"))


@q("SELECT p_partkey, CAST(CAST(p_retailprice AS DECIMAL(12, 2)) AS DOUBLE) AS price, TRY_CAST(p_brand AS INTEGER) AS bad, nullif(p_size, 1) AS size_, coalesce(nullif(p_size, 1), -1) AS filled FROM part")
def fn_cast_decimal_null(s: SparkSession, d: str) -> DataFrame:
    n = F.nullif("p_size", F.lit(1))
    return T.load(s, d, "part").select("p_partkey", F.col("p_retailprice").cast("decimal(12,2)").cast("double").alias("price"), F.expr("try_cast(p_brand as int)").alias("bad"), n.alias("size_"), F.coalesce(n, F.lit(-1)).alias("filled"))


@q("SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS first_id FROM documents")
def app_near_dup_copies(s: SparkSession, d: str) -> DataFrame:
    """Rows of equal text: each with the first of its class, from digests counted map-side; no pairs are made."""
    t = T.load(s, d, "documents").select("doc_id", F.sha2("text", 256).alias("h"))
    first = t.groupBy("h").agg(F.min("doc_id").alias("first_id"), F.count("*").alias("n")).where("n > 1")
    return t.join(first, "h", "left").select("doc_id", F.coalesce("first_id", "doc_id").alias("first_id"))


TERMS = "SELECT doc_id AS row_id, CAST('0x' || substr(md5(w), 1, 8) AS BIGINT) % 256 AS c, ln(1 + count(*)) AS v FROM (SELECT doc_id, unnest(string_split_regex(lower(coalesce(text, '')), '\\s+')) AS w FROM documents) GROUP BY 1, 2"
PAIRS = f"""WITH t AS MATERIALIZED ({TERMS}), n AS (SELECT row_id, sqrt(sum(v * v)) AS n FROM t GROUP BY 1),
u AS MATERIALIZED (SELECT row_id, string_agg(c || ':' || round(v, 9), ',' ORDER BY c) AS key FROM t GROUP BY 1), first AS (SELECT min(row_id) AS row_id FROM u GROUP BY key),
x AS MATERIALIZED (SELECT t.row_id, c, v / n AS v FROM t JOIN n USING (row_id) JOIN first USING (row_id))
SELECT CAST(a.row_id AS BIGINT) AS a, CAST(b.row_id AS BIGINT) AS b, round(sum(a.v * b.v), 6) + 0.0 AS cosine FROM x a JOIN x b ON a.c = b.c AND a.row_id < b.row_id GROUP BY 1, 2 HAVING sum(a.v * b.v) >= 0.98"""


@q(PAIRS)
def app_near_dup_pairs(s: SparkSession, d: str) -> DataFrame:
    """Pairs of class representatives of the documents' term rows with cosine of at least 0.98, found by projection."""
    from tilerank.operators import apps

    rows = apps.term_rows(T.load(s, d, "documents"), 256)
    return apps.near_pairs(rows, 256, 0.98).select("a", "b", r6(F.col("cosine"), "cosine"))


@q(f"""WITH t AS MATERIALIZED ({TERMS}), u AS MATERIALIZED (SELECT row_id, string_agg(c || ':' || round(v, 9), ',' ORDER BY c) AS key FROM t GROUP BY 1)
SELECT CAST(row_id AS BIGINT) AS doc_id, CAST(min(row_id) OVER (PARTITION BY key) AS BIGINT) AS first_id FROM u""")
def app_near_dup_classes(s: SparkSession, d: str) -> DataFrame:
    """Membership beside the pairs: each document with the first of those with the same term row."""
    from tilerank.operators import apps

    return apps.term_classes(apps.term_rows(T.load(s, d, "documents"), 256)).select(F.col("row_id").alias("doc_id"), "first_id")


ORACLES["agg_trace_powers"] = f"""WITH e AS ({G.SUPPMONTH}), h AS (SELECT a.col_id AS i, b.col_id AS j, sum(a.v * b.v) AS v FROM e a JOIN e b USING (row_id) GROUP BY 1, 2)
SELECT CAST(2 AS BIGINT) AS p, round((SELECT sum(v * v) FROM h) / power((SELECT sum(v) FROM h WHERE i = j), 2), 6) + 0.0 AS v"""


def agg_trace_powers(s: SparkSession, d: str) -> DataFrame:
    """Trace of the squared Gram matrix over the squared trace."""
    g = gram_entries(T.entries(T.suppmonth(s, d)))
    total = g.agg(F.sum(F.col("g") ** 2).alias("two"), F.sum(F.when(F.col("i") == F.col("j"), F.col("g"))).alias("one"))
    return total.select(F.lit(2).cast("bigint").alias("p"), r6(F.col("two") / F.col("one") ** 2, "v"))


QUERIES["agg_trace_powers"] = agg_trace_powers
