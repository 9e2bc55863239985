"""``factorize``: a factorization of what a SQL text returns, with the schedule that fits its size."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, NumericType

from tilerank.plans import costmodel
from tilerank.sources import tables

from . import baselines, reflect, sketchqr, utv
from .matrix import Tall, write_step


def as_rows(df: DataFrame, key: str | None = None) -> DataFrame:
    """(key, array) or (key, numbers...) -> row frame. The key is the first column unless named."""
    key = key or df.columns[0]
    rest = [f for f in df.schema if f.name != key]
    if len(rest) == 1 and isinstance(rest[0].dataType, ArrayType):
        return tables.rows_from_array(df, key, rest[0].name)
    if not rest or not all(isinstance(f.dataType, NumericType) for f in rest):
        raise ValueError("needs a key and an array of numbers, or a key and columns of numbers")
    return tables.rows_from_columns(df, F.col(key).cast("long"), [F.col(f"`{f.name}`") for f in rest])


def factorize(spark: SparkSession, sql: str, method: str = "utv", k: int | None = None, b: int = 64, key: str | None = None, store: bool = True, **options):
    """``method``: ``sketch_qr``, ``cpqr``, ``columnwise``, ``qr`` (reflectors), ``triangle``, ``utv`` or ``svd``.

    The query's rows are written once (``store``), so that its joins and shuffles don't come again with every pass. Sketched QR
    and UTV run on the triangle of one pass where n x n fits, else left-looking; matrices too wide for both need tiles and raise an error.
    """
    rows = as_rows(spark.sql(sql), key)
    mat = Tall(write_step(rows, "rows") if store else rows)
    if method in ("sketch_qr", "utv"):
        m, width = mat.df.count(), min(k or mat.n, mat.n)
        regime = options.pop("schedule", None) or costmodel.choose_regime(m, mat.n, width)
        if regime == "tiles":
            raise ValueError(f"{mat.n} columns need tiles: tilerank.operators.tiles.run_waves")
        if method == "utv":
            return utv.power_utv(mat, min(b, mat.n), k=k, schedule=regime, **options)
        return sketchqr.sketch_qr(mat, min(b, width), k, regime, **options)
    if method == "cpqr":
        return sketchqr.pivoted_qr(mat, k)
    if method == "columnwise":
        return sketchqr.pivoted_columnwise(mat, k or mat.n)
    if method == "qr":
        return reflect.reflector_qr(mat, min(b, mat.n), list(range(k or mat.n)))
    if method == "triangle":
        return mat.triangle()
    if method == "svd":
        return baselines.svd_dense(mat)
    raise ValueError(f"no method {method}")
