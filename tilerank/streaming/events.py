"""Streaming forms of the sums that sketches and triangles are made of.

Row sums merge, so a stream's norms, Gram entries, sketches and triangles equal those of a batch over the same rows.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor

from tilerank.functions import kernels as K
from tilerank.functions.keyed import gaussians
from tilerank.operators.matrix import shared_root

WATERMARK = "1 hour"


def root_of(spark: SparkSession) -> str:
    return f"{shared_root(spark)}/streams-{uuid.uuid4().hex}"


def read_events(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """The events table as a file stream; ``files`` a trigger."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    path = f"{sf_dir}/events.parquet"
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    return stream.option("pathGlobFilter", "events.parquet").parquet(sf_dir) if not path.endswith("/") and is_file(spark, path) else stream.parquet(path)


def is_file(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isFile()


def settle(df: DataFrame, mode: str, keys: list[str] | None = None) -> DataFrame:
    """Run a stream over what is there and return the final table: all batches, the last of each key under ``update``."""
    spark, root = df.sparkSession, root_of(df.sparkSession)
    out = f"{root}/out"

    def keep(batch: DataFrame, n: int) -> None:
        batch.withColumn("batch__", F.lit(n)).write.mode("overwrite").parquet(f"{out}/batch={n}")  # idempotent by batch

    query = df.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/state").foreachBatch(keep).trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.parquet(out).drop("batch")
    if mode == "append":
        return rows.drop("batch__")
    if mode == "complete":
        last = rows.agg(F.max("batch__")).first()[0]
        return rows.where(F.col("batch__") == last).drop("batch__")
    rest = [c for c in rows.columns if c not in (*keys, "batch__")]
    latest = rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch__").alias("r"))
    return latest.select(*keys, "r.*")


def tumbling_norms(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", WATERMARK).groupBy(F.window("ts", "1 day"), "event_type").agg(F.sum(F.col("value") ** 2).alias("e"))


def sliding_counts(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", WATERMARK).groupBy(F.window("ts", "6 hours", "2 hours")).agg(F.count("*").alias("n"))


def sessions(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", WATERMARK).groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n"))


def hour_gram(events: DataFrame) -> DataFrame:
    """Gram entries of the (event type x hour) indicator rows, weighted by value: diagonal blocks only are not zero."""
    return events.groupBy("event_type", F.hour("ts").alias("h")).agg(F.sum(F.col("value") ** 2).alias("g"))


ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


@contextmanager
def processors(spark: SparkSession):
    """Queries started inside keep their state in RocksDB, which stateful processors need (a setting of the running session)."""
    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name)
    spark.conf.set(name, ROCKS)
    try:
        yield
    finally:
        spark.conf.set(name, before)


class SketchKeeper(StatefulProcessor):
    """For each key the sketch of its rows, ``width`` x ``n`` numbers in a value state: row e of key k adds g(e, s) * value at column ``col``.

    State that no row has touched for ``ttl_ms`` goes.
    """

    def __init__(self, width: int, n: int, seed: int, ttl_ms: int | None = None):
        self.width, self.n, self.seed, self.ttl_ms = width, n, seed, ttl_ms

    def init(self, handle) -> None:
        self.held = handle.getValueState("sketch", "y array<double>", self.ttl_ms)

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        y = np.array(self.held.get()[0]).reshape(self.width, self.n) if self.held.exists() else np.zeros((self.width, self.n))
        for f in rows:
            g = gaussians(self.seed, f["event_id"].tolist(), self.width) * f["value"].to_numpy()[:, None]
            np.add.at(y.T, f["col"].to_numpy(), g)
        self.held.update((y.ravel().tolist(),))
        order = K.pivoted(y, self.width)[0][: self.width]
        yield pd.DataFrame({"user_id": [key[0]], "y": [y.ravel().tolist()], "pivots": [[int(p) for p in order]]})

    def close(self) -> None:
        pass


def user_sketch(events: DataFrame, width: int, seed: int, ttl_ms: int | None = None) -> DataFrame:
    """A sketch of each user's events by hour, kept in state, and the columns that it would pivot on first.

    Start it inside ``processors``.
    """
    rows = events.select("user_id", "event_id", "value", F.hour("ts").alias("col"))
    keeper = SketchKeeper(width, 24, seed, ttl_ms)
    return rows.groupBy("user_id").transformWithStateInPandas(keeper, "user_id bigint, y array<double>, pivots array<int>", "Update", "None" if ttl_ms is None else "ProcessingTime")


def incremental_triangle(events: DataFrame, columns: list[str], root: str | None = None) -> np.ndarray:
    """R of the event rows, merged batch by batch.

    A batch's triangle is a table of its own, ``triangles/batch=n``, put there anew if the batch comes again: a batch counts once however often it is
    seen, and a run that starts again on the same ``root`` goes on from the stream's checkpoint with all triangles there.
    """
    spark = events.sparkSession
    root = root or root_of(spark)
    n = len(columns)

    def merge(batch: DataFrame, number: int) -> None:
        from tilerank.operators.matrix import Tall

        if batch.isEmpty():
            return
        rows = batch.select(F.col("event_id").alias("row_id"), F.array(*[F.col(c).cast("double") for c in columns]).alias("x"))
        r = Tall(rows, n).triangle()
        made = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(r)], "i int, r array<double>")
        made.coalesce(1).write.mode("overwrite").parquet(f"{root}/triangles/batch={number}")

    events.writeStream.option("checkpointLocation", f"{root}/state").foreachBatch(merge).trigger(availableNow=True).start().awaitTermination()
    return stored_triangle(spark, root, n)


def stored_triangle(spark: SparkSession, root: str, n: int) -> np.ndarray:
    """The triangle of all batches' triangles: n rows a batch, combined by a tree."""
    from tilerank.operators.matrix import Tall

    held = spark.read.schema("i int, r array<double>, batch bigint").parquet(f"{root}/triangles")
    return Tall(held.select((F.col("batch") * n + F.col("i")).alias("row_id"), F.col("r").alias("x")), n).triangle()


def closing(rows: DataFrame, ts: str = "ts") -> DataFrame:
    """A table as a stream of three files: its rows, then twice a row ten years later, so that all windows of the table close."""
    root = root_of(rows.sparkSession)
    rows.coalesce(1).write.mode("append").parquet(f"{root}/in")
    for years in (10, 20):
        rows.limit(1).withColumn(ts, F.expr(f"timestamp'2100-01-01' + INTERVAL {years} YEAR")).coalesce(1).write.mode("append").parquet(f"{root}/in")
    return rows.sparkSession.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(f"{root}/in")


def daily_counts(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", WATERMARK).groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
