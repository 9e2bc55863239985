"""Matrices from and to files: text formats and Matrix Market through Spark, tiles of .npy files and random tiles through Python data
sources. A filter on tile rows or columns reaches those sources: they plan no partition, and make no tile, that it rules out."""

from __future__ import annotations

import io
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, In, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import StructType

from tilerank.functions.keyed import mixed

from .tables import TILE

READ_OPTIONS = {"csv": {"header": "true", "mode": "FAILFAST"}, "json": {"mode": "FAILFAST"}}


def read_matrix(spark: SparkSession, path: str, fmt: str, schema: StructType | str) -> DataFrame:
    """A table in csv, json, orc or parquet with a given schema; malformed rows fail."""
    return spark.read.options(**READ_OPTIONS.get(fmt, {})).schema(schema).format(fmt).load(path)


def write_matrix(df: DataFrame, path: str, fmt: str) -> None:
    df.write.options(**({"header": "true"} if fmt == "csv" else {})).format(fmt).save(path)


def write_matrix_market(e: DataFrame, path: str, m: int, n: int) -> None:
    """Entries as one coordinate file (the format knows no parts)."""
    lines = e.select(F.concat_ws(" ", F.col("row_id") + 1, F.col("col_id") + 1, F.col("v").cast("string")).alias("value"), F.lit(2).alias("place"))
    head = e.sparkSession.createDataFrame([("%%MatrixMarket matrix coordinate real general", 0), (f"{m} {n} {e.count()}", 1)], "value string, place int")
    head.union(lines).repartition(1).sortWithinPartitions("place").select("value").write.text(path)


def read_matrix_market(spark: SparkSession, path: str) -> DataFrame:
    """Entry frame of a coordinate file (real or integer; general or symmetric, whose other half is added)."""
    text = spark.read.text(path).withColumn("at", F.monotonically_increasing_id())
    head = text.where("value like '!%!%MatrixMarket%' escape '!'").first()
    kinds = head["value"].lower().split() if head else []
    if len(kinds) < 5 or kinds[2] != "coordinate" or kinds[3] not in ("real", "integer") or kinds[4] not in ("general", "symmetric"):
        raise ValueError("no coordinate matrix of numbers")
    body = text.where("value not like '!%%' escape '!' and trim(value) <> ''")
    size = body.agg(F.min("at")).first()[0]  # the line with the size comes first
    part = F.split(F.trim("value"), "[ \t]+")
    e = body.where(F.col("at") != size).select((part[0].cast("long") - 1).alias("row_id"), (part[1].cast("int") - 1).alias("col_id"), part[2].cast("double").alias("v"))
    if kinds[4] == "symmetric":
        e = e.union(e.where("row_id <> col_id").select(F.col("col_id").cast("long"), F.col("row_id").cast("int"), "v"))
    return e


def open_store(uri: str) -> tuple[pafs.FileSystem, str]:
    if uri.startswith("file:"):
        uri = uri[5:].replace("//", "/", 1) if uri.startswith("file:///") else uri[5:]
    return pafs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri}")


def write_npy(rows: DataFrame, path: str, n: int) -> None:
    """A small row frame as one .npy file, by the driver."""
    a = np.array([r["x"] for r in rows.orderBy("row_id").toLocalIterator()], float).reshape(-1, n)
    held = io.BytesIO()
    np.save(held, a)
    store, place = open_store(path)
    store.create_dir(place.rpartition("/")[0], recursive=True)
    with store.open_output_stream(place) as out:
        out.write(held.getvalue())


def register(spark: SparkSession) -> None:
    """Make ``tilematrix`` and ``matrixfile`` known, with filters pushed to them (a setting of the running session)."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(RandomTiles)
    spark.dataSource.register(MatrixFile)


class TileRow(InputPartition):
    def __init__(self, bi: int):
        self.bi = bi


class TileReader(DataSourceReader):
    """Keeps to the tile rows and columns that pushed filters leave; a partition is a tile row."""

    def __init__(self, m: int, n: int, b: int):
        self.m, self.n, self.b = m, n, b
        self.rows, self.cols = range(-(-m // b)), range(-(-n // b))

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        for f in filters:
            name = f.attribute[0] if getattr(f, "attribute", None) and len(f.attribute) == 1 else None
            test = {
                EqualTo: lambda x, v: x == v, GreaterThan: lambda x, v: x > v, GreaterThanOrEqual: lambda x, v: x >= v,
                LessThan: lambda x, v: x < v, LessThanOrEqual: lambda x, v: x <= v, In: lambda x, v: x in v,
            }.get(type(f))
            if test and name in ("bi", "bj"):
                kept = [x for x in (self.rows if name == "bi" else self.cols) if test(x, f.value)]
                self.rows, self.cols = (kept, self.cols) if name == "bi" else (self.rows, kept)
            else:
                yield f

    def partitions(self) -> list[TileRow]:
        return [TileRow(i) for i in self.rows]

    def block(self, lo: int, hi: int, j: int, c: int) -> np.ndarray:
        raise NotImplementedError

    def read(self, partition: TileRow) -> Iterator[pa.RecordBatch]:
        i, b = partition.bi, self.b
        lo, hi = i * b, min(self.m, (i + 1) * b)
        for j in self.cols:
            c = min(b, self.n - j * b)
            data = np.ascontiguousarray(self.block(lo, hi, j * b, c), dtype=float)
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([j], pa.int32()), pa.array([hi - lo], pa.int32()), pa.array([c], pa.int32()), pa.array([data.tobytes()], pa.binary())], names=["bi", "bj", "nr", "nc", "data"])


class RandomTiles(DataSource):
    """``format("tilematrix")``: tiles of a keyed random matrix. Options m, n, b, seed."""

    @classmethod
    def name(cls) -> str:
        return "tilematrix"

    def schema(self) -> str:
        return TILE

    def reader(self, schema: StructType) -> DataSourceReader:
        return RandomTilesReader(*(int(self.options.get(k, d)) for k, d in (("m", "64"), ("n", "64"), ("b", "16"), ("seed", "7"))))


class RandomTilesReader(TileReader):
    def __init__(self, m: int, n: int, b: int, seed: int):
        super().__init__(m, n, b)
        self.seed = seed

    def block(self, lo: int, hi: int, j: int, c: int) -> np.ndarray:
        return mixed(self.seed, np.arange(lo, hi), c, j)


class MatrixFile(DataSource):
    """``format("matrixfile")``: tiles of a .npy file of doubles or floats, row by row. Options path (any store that Arrow opens), b."""

    @classmethod
    def name(cls) -> str:
        return "matrixfile"

    def schema(self) -> str:
        return TILE

    def reader(self, schema: StructType) -> DataSourceReader:
        return MatrixFileReader(self.options["path"], int(self.options.get("b", "256")))


class MatrixFileReader(TileReader):
    def __init__(self, path: str, b: int):
        self.path = path
        store, place = open_store(path)
        with store.open_input_stream(place) as f:
            head = io.BytesIO(f.read(1 << 12))
        version = np.lib.format.read_magic(head)
        shape, by_column, self.kind = (np.lib.format.read_array_header_1_0 if version == (1, 0) else np.lib.format.read_array_header_2_0)(head)
        if by_column or len(shape) != 2 or self.kind.kind != "f":
            raise ValueError("needs a two-dimensional array of floats, row by row")
        self.start = head.tell()
        super().__init__(*shape, b)
        self.held: tuple = (None, None)

    def block(self, lo: int, hi: int, j: int, c: int) -> np.ndarray:
        if self.held[0] != lo:
            store, place = open_store(self.path)
            width = self.n * self.kind.itemsize
            with store.open_input_file(place) as f:
                raw = f.read_at((hi - lo) * width, self.start + lo * width)
            self.held = (lo, np.frombuffer(raw, self.kind).reshape(hi - lo, self.n))
        return self.held[1][:, j : j + c]
