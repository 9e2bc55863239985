"""Factors as tables: triangles, permutations, right factors and reflectors under one folder, with their shape beside them.

``meta`` is one JSON line (kind, k, n, perm, passes, format), ``r`` has a row of the triangle each, ``v`` a row of the right factor each,
and ``reflectors`` a folder for each step, so that a step is read by itself.
"""

from __future__ import annotations

import json
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilerank.operators.matrix import Tall, shared_root
from tilerank.operators.reflect import ReflectorQR
from tilerank.operators.sketchqr import PivotedQR
from tilerank.operators.utv import UTV

FORMAT = 1


def array_rows(spark: SparkSession, a: np.ndarray) -> DataFrame:
    return spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(a)], "i bigint, r array<double>")


def save_factor(spark: SparkSession, f: PivotedQR | UTV | ReflectorQR, path: str | None = None) -> str:
    """Write a factorization; -> its folder."""
    path = path or f"{shared_root(spark)}/factor-{uuid.uuid4().hex}"
    if isinstance(f, ReflectorQR):
        meta = {"kind": "reflectors", "k": len(f.columns), "n": f.mat.n, "perm": f.columns}
        f.reflectors().write.partitionBy("step").parquet(f"{path}/reflectors")
        array_rows(spark, f.r).write.parquet(f"{path}/r")
    elif isinstance(f, UTV):
        meta = {"kind": "utv", "k": f.k, "n": f.mat.n, "passes": f.passes}
        array_rows(spark, f.t).write.parquet(f"{path}/r")
        array_rows(spark, f.v).write.parquet(f"{path}/v")
    else:
        meta = {"kind": "pivoted", "k": f.k, "n": f.mat.n, "perm": f.perm, "passes": f.passes, "residual": f.residual}
        array_rows(spark, f.r).write.parquet(f"{path}/r")
    # the last to be written: a folder without it is no factor
    spark.createDataFrame([(json.dumps(meta | {"format": FORMAT}),)], "value string").coalesce(1).write.text(f"{path}/meta")
    return path


def read_meta(spark: SparkSession, path: str) -> dict:
    meta = json.loads(spark.read.text(f"{path}/meta").first()[0])
    if meta["format"] != FORMAT:
        raise ValueError(f"format {meta['format']} of {path} is not known")
    return meta


def read_triangle(spark: SparkSession, path: str) -> DataFrame:
    """(i, r): a row of the triangle each, columns in pivot order."""
    read_meta(spark, path)
    return spark.read.schema("i bigint, r array<double>").parquet(f"{path}/r")


def read_reflectors(spark: SparkSession, path: str, step: int | None = None) -> DataFrame:
    found = spark.read.parquet(f"{path}/reflectors")
    return found if step is None else found.where(F.col("step") == step)


def load_factor(spark: SparkSession, path: str, mat: Tall) -> PivotedQR | UTV:
    """A pivoted or UTV factorization of ``mat`` as it was saved."""
    meta = read_meta(spark, path)
    rows = lambda name: np.array([r["r"] for r in spark.read.parquet(f"{path}/{name}").orderBy("i").collect()]).reshape(-1, meta["n"])
    if mat.n != meta["n"]:
        raise ValueError(f"a factor of {meta['n']} columns")
    if meta["kind"] == "pivoted":
        return PivotedQR(mat, meta["perm"], rows("r"), meta["k"], meta["residual"], meta["passes"])
    if meta["kind"] == "utv":
        return UTV(mat, rows("r"), rows("v"), meta["k"], meta["passes"])
    raise ValueError(f"{meta['kind']} are read by read_reflectors")
