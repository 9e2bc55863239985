"""Tall matrices as immutable row frames, and passes over them.

A pass streams Arrow batches through a kernel that keeps one small array per task, and combines the tasks' arrays in a
tree; the driver sees FAN_IN of them at most, in a fixed order. Everything n x n or k x n is small in the tall regime
(n up to N_LOCAL) and travels with the task; nothing m long leaves the executors.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilerank.functions import kernels as K

N_LOCAL, FAN_IN = 16_384, 32
PART = "leaf int, nr int, nc int, data binary"


def block(batch: pa.RecordBatch, n: int, x: str = "x") -> np.ndarray:
    """The rows of a batch as a matrix, without copying."""
    lists = batch.column(batch.schema.get_field_index(x))
    flat = lists.flatten()
    if len(flat) != n * len(lists) or flat.null_count or lists.null_count:
        raise ValueError(f"every row needs {n} numbers")
    a = flat.to_numpy(zero_copy_only=False).reshape(-1, n)
    if not np.isfinite(a).all():
        raise ValueError("NaN or infinity in the matrix")
    return a


def packed(leaf: int, a: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([leaf], pa.int32()), pa.array([a.shape[0]], pa.int32()), pa.array([a.shape[1]], pa.int32()), pa.array([np.ascontiguousarray(a).tobytes()], pa.binary())], names=["leaf", "nr", "nc", "data"])


def unpacked(rows) -> list[np.ndarray]:
    return [np.frombuffer(r["data"]).reshape(r["nr"], r["nc"]) for r in sorted(rows, key=lambda r: r["leaf"])]


def add(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return a + b


class Tall:
    """``df`` (row_id, x) with n columns. ``passes`` counts the scans of it."""

    def __init__(self, df: DataFrame, n: int | None = None):
        self.df = df.select("row_id", "x")
        if n is None:
            first = self.df.select(F.size("x")).first()
            if first is None:
                raise ValueError("an empty table is no matrix")
            n = first[0]
        if n > N_LOCAL:
            raise ValueError(f"{n} columns are too many to keep n x n arrays on the driver; use tiles")
        self.n, self.passes, self._leaves = n, 0, None

    @classmethod
    def stored(cls, df: DataFrame, n: int | None = None) -> Tall:
        """Of a frame that takes a shuffle to make: written once, so that the passes only scan."""
        return cls(write_step(df.select("row_id", "x"), "rows"), n)

    @property
    def spark(self):
        return self.df.sparkSession

    def leaves(self) -> int:
        if self._leaves is None:
            self._leaves = self.df.rdd.getNumPartitions()
        return self._leaves

    def reduce(self, local: Callable[[np.ndarray, np.ndarray], np.ndarray], combine: Callable = add, fan_in: int = FAN_IN) -> np.ndarray | None:
        """``local(ids, block)`` of each batch, combined within tasks, then over tasks in a tree."""
        n = self.n
        self.passes += 1

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            from pyspark import TaskContext

            acc = None
            for batch in batches:
                if batch.num_rows:
                    got = local(batch.column(0).to_numpy(zero_copy_only=False), block(batch, n))
                    acc = got if acc is None else combine(acc, got)
            if acc is not None:
                yield packed(TaskContext.get().partitionId(), acc)

        def merge(t: pa.Table) -> pa.Table:
            parts = unpacked(t.to_pylist())
            acc = parts[0]
            for p in parts[1:]:
                acc = combine(acc, p)
            return pa.Table.from_batches([packed(min(t["leaf"].to_pylist()), acc)])

        parts, left = self.df.mapInArrow(run, PART), self.leaves()
        level = 1
        while left > fan_in:
            level *= fan_in
            parts = parts.groupBy(F.floor(F.col("leaf") / level).alias("g")).applyInArrow(merge, PART)
            left = -(-left // fan_in)
        acc = None
        for p in unpacked(r.asDict() for r in parts.collect()):
            acc = p if acc is None else combine(acc, p)
        return acc

    def map_rows(self, f: Callable[[np.ndarray, np.ndarray], np.ndarray], keep: bool = True) -> DataFrame:
        """Row-local: ``f(ids, block)`` -> new rows; a row frame."""
        n = self.n

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                out = np.ascontiguousarray(f(batch.column(0).to_numpy(zero_copy_only=False), block(batch, n)))
                w = out.shape[1]
                offsets = pa.array(np.arange(0, w * len(out) + 1, w, dtype=np.int32)) if len(out) else pa.array([0], pa.int32())
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(offsets, pa.array(out.ravel()))], names=["row_id", "x"])

        return self.df.mapInArrow(run, "row_id long, x array<double>")

    # products

    def gram(self) -> np.ndarray:
        return self.reduce(lambda _, a: a.T @ a)

    def times(self, x: np.ndarray) -> DataFrame:
        """A X for a small X."""
        return self.map_rows(lambda _, a: a @ x)

    def left(self, draw: Callable[[np.ndarray], np.ndarray]) -> np.ndarray:
        """H' A where ``draw(ids)`` gives the rows of H."""
        return self.reduce(lambda ids, a: draw(ids).T @ a)

    def gram_times(self, x: np.ndarray) -> np.ndarray:
        """A' (A X) in one pass, right to left."""
        return self.reduce(lambda _, a: a.T @ (a @ x))

    def frob(self) -> float:
        return float(np.sqrt(self.reduce(lambda _, a: np.array([[(a * a).sum()]]))[0, 0]))

    def spectral_norm(self) -> float:
        """Largest singular value, from the triangle of one pass."""
        return float(np.linalg.norm(self.triangle(), 2))

    def column_norms(self) -> np.ndarray:
        return np.sqrt(self.reduce(lambda _, a: (a * a).sum(0)[None, :])[0])

    def triangle(self, columns: list[int] | None = None, extra: Callable | None = None) -> np.ndarray:
        """R of the (chosen) columns, with ``extra(ids)`` beside them, by a reduction tree; diagonal not negative."""

        def local(ids: np.ndarray, a: np.ndarray) -> np.ndarray:
            c = a if columns is None else a[:, columns]
            return K.r_only(c if extra is None else np.hstack([c, extra(ids)]))

        r = self.reduce(local, K.r_only)
        n = r.shape[1]
        return K.positive(np.vstack([r, np.zeros((max(0, n - len(r)), n))]))


def stack(top: DataFrame, below: DataFrame) -> DataFrame:
    """Rows of two row frames of one width under each other; the lower ones' ids (from 0 on) follow the upper ones' largest."""
    last = top.agg(F.coalesce(F.max("row_id"), F.lit(-1))).first()[0]
    return top.select("row_id", "x").union(below.select(F.col("row_id") + last + 1, "x"))


def identity_rows(spark, n: int) -> DataFrame:
    """The identity as a row frame."""
    return spark.range(n).select(F.col("id").alias("row_id"), F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda j: F.when(j == F.col("id"), 1.0).otherwise(0.0)).alias("x"))


def equal_within(a: DataFrame, b: DataFrame, tol: float) -> bool:
    """Whether two row frames have the same row ids, and entries that differ by ``tol`` at most."""
    both = a.select("row_id", F.col("x").alias("p")).join(b.select("row_id", F.col("x").alias("q")), "row_id", "full")
    off = F.aggregate(F.zip_with("p", "q", lambda x, y: F.abs(x - y)), F.lit(0.0), lambda m, v: F.greatest(m, v))
    wrong = F.col("p").isNull() | F.col("q").isNull() | (F.size("p") != F.size("q")) | ~(off <= tol)
    return both.where(wrong).isEmpty()


def shared_root(spark) -> str:
    """A folder that driver and executors share: ``spark.checkpoint.dir``; the warehouse only where that is unset and the master is local."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        root = spark.conf.get("spark.sql.warehouse.dir")
    return f"{root.rstrip('/')}/steps"


def write_step(df: DataFrame, label: str) -> DataFrame:
    """Write a step's frame to the shared folder and read it back: a restart point that cuts the lineage."""
    spark = df.sparkSession
    path = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def with_index(df: DataFrame, key: str = "row_id", out: str = "idx") -> DataFrame:
    """Consecutive numbers by ``key``: range partitions are counted, their offsets sent to each, rows numbered inside.

    No window spans the table; the offsets are a number for each partition.
    """
    from pyspark.sql.window import Window

    ordered = write_step(df.repartitionByRange(key).sortWithinPartitions(key).withColumn("part__", F.spark_partition_id()), "ordered")
    sizes = {r["part__"]: r["count"] for r in ordered.groupBy("part__").count().collect()}
    offsets, total = {}, 0
    for p in sorted(sizes):
        offsets[p], total = total, total + sizes[p]
    if not sizes:
        return df.withColumn(out, F.lit(0).cast("long")).limit(0)
    start = F.element_at(F.create_map(*[F.lit(int(v)) for kv in offsets.items() for v in kv]), F.col("part__"))
    number = F.row_number().over(Window.partitionBy("part__").orderBy(key))
    return ordered.withColumn(out, (start + number - 1).cast("long")).drop("part__")
