"""Loading the given tables and building matrices from them.

A matrix is a row frame (``row_id``, ``x`` array of doubles), an entry frame (``row_id``, ``col_id``, ``v``) or a tile
frame (``bi``, ``bj``, ``nr``, ``nc``, ``data`` of little-endian doubles, row by row).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
TILE = "bi int, bj int, nr int, nc int, data binary"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"no table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checked(x: Column, nulls: str = "error") -> Column:
    """Doubles without NULL: an error, zero, or left for the caller's filter (``drop_row``)."""
    d = x.cast("double")
    if nulls == "error":
        return F.coalesce(d, F.raise_error(F.lit("NULL in a matrix column")).cast("double"))
    return F.coalesce(d, F.lit(0.0)) if nulls == "zero" else d


def rows_from_columns(df: DataFrame, key: Column, columns: list[Column], nulls: str = "error") -> DataFrame:
    """Numeric columns side by side -> row frame."""
    if nulls == "drop_row":
        keep = F.lit(True)
        for c in columns:
            keep = keep & c.isNotNull()
        df = df.where(keep)
    return df.select(key.alias("row_id"), F.array(*[checked(c, nulls) for c in columns]).alias("x"))


def rows_from_array(df: DataFrame, key: str, array: str) -> DataFrame:
    return df.select(F.col(key).cast("long").alias("row_id"), F.col(array).cast("array<double>").alias("x"))


def entries(rows: DataFrame) -> DataFrame:
    """Row frame -> entry frame."""
    return rows.select("row_id", F.posexplode("x").alias("col_id", "v"))


def rows_from_entries(e: DataFrame, n: int) -> DataFrame:
    """Entry frame -> row frame of width n; entries at the same place are summed, missing ones are zero."""
    summed = e.groupBy("row_id", "col_id").agg(F.sum("v").alias("v"))
    m = summed.groupBy("row_id").agg(F.map_from_entries(F.collect_list(F.struct("col_id", "v"))).alias("m"))
    return m.select("row_id", F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda j: F.coalesce(F.element_at("m", j), F.lit(0.0))).alias("x"))


def pivot_rows(df: DataFrame, key: Column, column: Column, value: Column, n: int) -> DataFrame:
    """Sum of ``value`` by key and column number 0..n-1 -> row frame."""
    return rows_from_entries(df.select(key.alias("row_id"), column.cast("int").alias("col_id"), value.cast("double").alias("v")), n)


def to_tiles(e: DataFrame, b: int, n: int, m: int) -> DataFrame:
    """Entry frame (row_id 0..m-1) -> tiles of b x b, ragged at the edges; tiles without entries are not stored."""

    def dense(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
        bi, bj = key[0].as_py(), key[1].as_py()
        a = np.zeros((min(b, m - bi * b), min(b, n - bj * b)))
        np.add.at(a, (t["row_id"].to_numpy() - bi * b, t["col_id"].to_numpy() - bj * b), t["v"].to_numpy())
        return pa.table({"bi": pa.array([bi], pa.int32()), "bj": pa.array([bj], pa.int32()), "nr": pa.array([a.shape[0]], pa.int32()), "nc": pa.array([a.shape[1]], pa.int32()), "data": [a.tobytes()]})

    keyed = e.withColumn("bi", F.floor(F.col("row_id") / b).cast("int")).withColumn("bj", F.floor(F.col("col_id") / b).cast("int"))
    return keyed.groupBy("bi", "bj").applyInArrow(dense, TILE)


def from_tiles(tiles: DataFrame, b: int) -> DataFrame:
    """Tiles -> entry frame, zeros included; small tiles share a batch."""

    def run(batches):
        for t in batches:
            held, size = [], 0
            for bi, bj, nr, nc, data in zip(*(t.column(c).to_pylist() for c in ("bi", "bj", "nr", "nc", "data")), strict=True):
                i, j = np.divmod(np.arange(nr * nc), nc)
                held.append((i + bi * b, (j + bj * b).astype(np.int32), np.frombuffer(data)))
                size += nr * nc
                if size >= 65_536:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held, strict=True)], names=["row_id", "col_id", "v"])
                    held, size = [], 0
            if held:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held, strict=True)], names=["row_id", "col_id", "v"])

    return tiles.mapInArrow(run, "row_id long, col_id int, v double")


def transpose_tiles(tiles: DataFrame) -> DataFrame:
    """Each tile in place, its keys swapped: no shuffle."""

    def run(batches):
        for t in batches:
            data = [np.frombuffer(d).reshape(r, c).T.tobytes() for d, r, c in zip(*(t.column(x).to_pylist() for x in ("data", "nr", "nc")), strict=True)]
            yield pa.RecordBatch.from_arrays([t.column("bj"), t.column("bi"), t.column("nc"), t.column("nr"), pa.array(data, pa.binary())], names=["bi", "bj", "nr", "nc", "data"])

    return tiles.mapInArrow(run, TILE)


def to_slabs(rows: DataFrame, size: int) -> DataFrame:
    """Row frame -> (slab, row_id, x): consecutive rows by id in slabs of ``size``, without a window over the table."""
    from tilerank.operators.matrix import with_index

    return with_index(rows, "row_id", "place").select(F.floor(F.col("place") / size).alias("slab"), "row_id", "x")


def select_columns(rows: DataFrame, columns: list[int]) -> DataFrame:
    """Columns by number, in the order given: a selection, a permutation or both."""
    return rows.select("row_id", F.array(*[F.get("x", F.lit(c)) for c in columns]).alias("x"))


def scaled(rows: DataFrame, n: int, centre: bool = True, scale: bool = True) -> DataFrame:
    """Columns less their means and over their standard deviations; a constant column stays zero."""
    one = rows.agg(*[f(F.get("x", F.lit(j))) for f in (F.avg, F.stddev_pop) for j in range(n)]).first()
    means, sds = ([float(one[j]) if centre else 0.0 for j in range(n)], [float(one[n + j]) or 1.0 if scale else 1.0 for j in range(n)])
    return rows.select("row_id", F.array(*[(F.get("x", F.lit(j)) - F.lit(means[j])) / F.lit(sds[j]) for j in range(n)]).alias("x"))


# the carrier matrices


def emb(spark: SparkSession, d: str) -> DataFrame:
    return rows_from_array(load(spark, d, "embeddings"), "vec_id", "embedding")


def line_key() -> Column:
    return F.xxhash64("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate")


LINE4 = ("l_quantity", "l_extendedprice", "l_discount", "l_tax")


def line4(spark: SparkSession, d: str) -> DataFrame:
    return rows_from_columns(load(spark, d, "lineitem"), line_key(), [F.col(c) for c in LINE4])


def design_columns() -> list[Column]:
    price, disc = F.col("l_extendedprice"), F.col("l_discount")
    flags = [(F.col("l_returnflag") == x).cast("double") for x in "ANR"]
    status = [(F.col("l_linestatus") == x).cast("double") for x in "OF"]
    return [F.lit(1.0), F.col("l_quantity"), price, disc, F.col("l_tax"), price * (1 - disc), price * disc, *flags, *status]


def design(spark: SparkSession, d: str) -> DataFrame:
    """Columns of unit norm; three exact dependencies leave rank 9 of 12."""
    rows = rows_from_columns(load(spark, d, "lineitem"), line_key(), design_columns())
    norms = rows.agg(*[F.sqrt(F.sum(F.get("x", F.lit(j)) ** 2)) for j in range(12)]).first()
    return rows.select("row_id", F.array(*[F.get("x", F.lit(j)) / float(norms[j] or 1.0) for j in range(12)]).alias("x"))


def userhour(spark: SparkSession, d: str) -> DataFrame:
    return pivot_rows(load(spark, d, "events"), F.col("user_id"), F.hour("ts"), F.col("value"), 24)


def suppmonth(spark: SparkSession, d: str) -> DataFrame:
    li = load(spark, d, "lineitem").where((F.col("l_shipdate") >= "1995-01-01") & (F.col("l_shipdate") < "1996-01-01"))
    return pivot_rows(li, F.col("l_suppkey"), F.month("l_shipdate") - 1, F.col("l_quantity"), 12)


def supppart(spark: SparkSession, d: str) -> DataFrame:
    """Entries: supplier x part number modulo 64, quantities summed."""
    li = load(spark, d, "lineitem")
    return li.groupBy(F.col("l_suppkey").alias("row_id"), F.pmod("l_partkey", F.lit(64)).cast("int").alias("col_id")).agg(F.sum("l_quantity").alias("v"))
