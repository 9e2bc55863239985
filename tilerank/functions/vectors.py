"""Row-vector algebra in JVM functions, and the same as UDFs and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType, StructField, StructType

from .keyed import gaussians


def vec_dot(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def vec_norm(x: Column) -> Column:
    return F.sqrt(F.aggregate(x, F.lit(0.0), lambda s, v: s + v * v))


def vec_scale(a: Column, x: Column) -> Column:
    return F.transform(x, lambda v: a * v)


def vec_axpy(a: Column, x: Column, y: Column) -> Column:
    return F.zip_with(x, y, lambda u, v: a * u + v)


def vec_givens(x: Column, i: int, j: int) -> Column:
    """(c, s, r) that rotates entry j into entry i."""
    a, b = F.get(x, F.lit(i)), F.get(x, F.lit(j))
    r = F.hypot(a, b)
    return F.struct(F.when(r == 0, 1.0).otherwise(a / r).alias("c"), F.when(r == 0, 0.0).otherwise(b / r).alias("s"), r.alias("r"))


def house(x: Column) -> Column:
    """(alpha, beta) of the reflector that sends x to alpha e1."""
    n, first = vec_norm(x), F.get(x, F.lit(0))
    alpha = F.when(first >= 0, -n).otherwise(n)
    return F.struct(alpha.alias("alpha"), F.when(n == 0, 0.0).otherwise((alpha - first) / alpha).alias("beta"))


@F.pandas_udf(DoubleType())
def tile_norm(data: pd.Series) -> pd.Series:
    return data.map(lambda d: float(np.linalg.norm(np.frombuffer(d))))


@F.pandas_udf(DoubleType())
def array_norm(x: pd.Series) -> pd.Series:
    return x.map(lambda v: float(np.linalg.norm(v)))


@F.pandas_udf(DoubleType())
def tile_sum(data: pd.Series) -> float:
    """Sum of all entries of a group's tiles."""
    return float(sum(np.frombuffer(d).sum() for d in data))


@F.udtf(returnType=StructType([StructField("row_id", LongType()), StructField("col", LongType()), StructField("v", DoubleType())]))
class TileEntries:
    """Entries of one tile."""

    def eval(self, data: bytes, bi: int, bj: int, nr: int, nc: int, b: int) -> Iterator[tuple]:
        for i, row in enumerate(np.frombuffer(data).reshape(nr, nc)):
            for j, v in enumerate(row):
                yield bi * b + i, bj * b + j, float(v)


@F.udtf(returnType=StructType([StructField("row_id", LongType()), StructField("col", LongType()), StructField("g", DoubleType())]))
class KeyedGaussians:
    def eval(self, rows: int, cols: int, seed: int) -> Iterator[tuple]:
        for i, row in enumerate(gaussians(seed, range(rows), cols)):
            for j, v in enumerate(row):
                yield i, j, float(v)


def row_norms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(row_id, x) -> (row_id, nrm)."""
    for b in batches:
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array([float(np.linalg.norm(v)) for v in b.column(1).to_pylist()], pa.float64())], names=["row_id", "nrm"])


def register_all(spark: SparkSession) -> None:
    """Functions for SQL texts."""
    for name, f in (("tile_norm", tile_norm), ("array_norm", array_norm), ("tile_sum", tile_sum)):
        spark.udf.register(name, f)
    spark.udtf.register("tile_entries", TileEntries)
    spark.udtf.register("keyed_gaussians", KeyedGaussians)
