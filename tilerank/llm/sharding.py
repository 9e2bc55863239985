"""Size-tiered compaction of immutable shards under a versioned manifest.

Arrivals are appended as small runs (Parquet folders that are never changed). A tier holds runs whose size is
within a factor FANOUT of each other; as soon as a tier has FANOUT runs, those are merged into one run with files of
about the target size, and the result moves up. Every change commits a new manifest version: the list of live runs,
written by Spark's own manager of checkpoint files (an atomic create that fails if the version exists, by rename or, in object
stores, by the manager that ``spark.sql.streaming.checkpointFileManagerClass`` names), so that
readers see a whole version or the one before, and a lost writer leaves nothing but unlisted files.

A merge keeps the runs it replaced, since older versions name them; ``expire`` forgets old versions and removes the runs, and what lost
writers left, that no kept version names.

Only DataFrame operations touch rows; the driver handles the manifest (a line for each run).

Defined cases: nulls and repeated rows are stored as they are; an empty arrival adds no run; any columns are kept
under their names, and where one is called ``shard_run`` or ``shard_tier`` the added column's name gets an underscore; a merge of a
crash-interrupted run is repeated under a new name.
"""

from __future__ import annotations

import json
import time
import uuid
from dataclasses import asdict, dataclass

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import free_name

FANOUT, TARGET_BYTES = 4, 128 << 20


def file_manager(spark: SparkSession, folder):
    """Spark's manager of checkpoint files for a folder: creates files whole, or not at all if they exist."""
    package = spark.sparkContext._jvm.org.apache.spark.sql.execution.streaming.checkpointing
    return package.CheckpointFileManager.create(folder, spark.sparkContext._jsc.hadoopConfiguration())


@dataclass(frozen=True)
class Run:
    """One immutable folder: rows, bytes on disk, tier, and the arrivals it holds (first and last)."""

    name: str
    rows: int
    size: int
    tier: int
    first: int
    last: int


class ShardSet:
    """Runs under ``root`` (any file system that Spark writes); ``version`` 0 has none."""

    def __init__(self, spark: SparkSession, root: str, fanout: int = FANOUT, target_bytes: int = TARGET_BYTES, small_bytes: int = 4 << 20):
        if fanout < 2:
            raise ValueError("a merge takes two runs or more")
        self.spark, self.root, self.fanout, self.target, self.small = spark, root.rstrip("/"), fanout, target_bytes, small_bytes
        self.jvm = spark.sparkContext._jvm
        self.fs = self.path("").getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def path(self, name: str):
        return self.jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}" if name else self.root)

    # manifest

    def version(self) -> int:
        return max(self.versions(), default=0)

    def runs(self, version: int | None = None) -> list[Run]:
        version = self.version() if version is None else version
        if not version:
            return []
        stream = self.fs.open(self.path(f"manifest/v{version}"))
        try:
            text = self.jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()
        return [Run(**json.loads(line)) for line in text.splitlines()]

    def commit(self, runs: list[Run], base: int) -> int:
        """Publish ``runs`` as version ``base + 1``; raises if another writer was first."""
        folder = self.path("manifest")
        self.fs.mkdirs(folder)
        files = file_manager(self.spark, folder)
        goal = self.path(f"manifest/v{base + 1}")
        try:
            if files.exists(goal):
                raise RuntimeError(f"version {base + 1} was committed by another writer")
            out = files.createAtomic(goal, False)
            try:
                out.write(bytearray("\n".join(json.dumps(asdict(r)) for r in runs).encode()))
                out.close()
            except BaseException:
                out.cancel()
                raise
        except Py4JJavaError as e:
            if "FileAlreadyExists" in e.java_exception.toString():
                raise RuntimeError(f"version {base + 1} was committed by another writer") from e
            raise
        return base + 1

    def versions(self) -> list[int]:
        folder = self.path("manifest")
        if not self.fs.exists(folder):
            return []
        names = [s.getPath().getName() for s in self.fs.listStatus(folder)]
        return sorted(int(n[1:]) for n in names if n[:1] == "v" and n[1:].isdigit())

    def expire(self, keep: int = 1, older_s: float = 86_400.0) -> list[str]:
        """Forget all but the last ``keep`` versions, then remove folders that no kept version names and that are older than ``older_s`` seconds.

        Runs of writers at work are younger than that. -> names of the folders removed.
        """
        known = self.versions()
        kept = known[-max(1, keep) :]
        named = {r.name for v in kept for r in self.runs(v)}
        for v in known[: len(known) - len(kept)]:
            self.fs.delete(self.path(f"manifest/v{v}"), False)
        bound = (time.time() - older_s) * 1000
        gone = []
        for s in self.fs.listStatus(self.path("")):
            name = s.getPath().getName()
            if name.startswith(("run-", "dealt-")) and name not in named and s.getModificationTime() <= bound:
                self.fs.delete(s.getPath(), True)
                gone.append(name)
        return sorted(gone)

    # rows

    def tier_of(self, size: int) -> int:
        tier, bound = 0, self.small
        while size > bound:
            tier, bound = tier + 1, bound * self.fanout
        return tier

    def write_run(self, rows: DataFrame, first: int, last: int, files: int | None) -> Run | None:
        name = f"run-{first:06d}-{last:06d}-{uuid.uuid4().hex[:8]}"
        (rows if files is None else rows.coalesce(max(1, files))).write.parquet(f"{self.root}/{name}")
        folder = self.path(name)
        size = self.fs.getContentSummary(folder).getLength()
        count = self.spark.read.schema(rows.schema).parquet(f"{self.root}/{name}").count()
        if not count:
            self.fs.delete(folder, True)
            return None
        return Run(name, count, size, self.tier_of(size), first, last)

    def append(self, rows: DataFrame) -> int:
        """Store an arrival as a small run and commit it; -> version."""
        base, runs = self.version(), self.runs()
        arrival = max((r.last for r in runs), default=-1) + 1
        run = self.write_run(rows, arrival, arrival, None)
        return self.commit([*runs, run], base) if run else base

    def adopt(self, folder: str, schema) -> int:
        """Commit a written folder under the root as the next arrival."""
        base, runs = self.version(), self.runs()
        arrival = max((r.last for r in runs), default=-1) + 1
        name = f"run-{arrival:06d}-{arrival:06d}-{uuid.uuid4().hex[:8]}"
        if not self.fs.rename(self.path(folder), self.path(name)):
            raise RuntimeError(f"{folder} could not be moved")
        size = self.fs.getContentSummary(self.path(name)).getLength()
        count = self.spark.read.schema(schema).parquet(f"{self.root}/{name}").count()
        return self.commit([*runs, Run(name, count, size, self.tier_of(size), arrival, arrival)], base)

    def merge_once(self, schema) -> bool:
        """Merge the FANOUT oldest runs of the lowest full tier; -> whether there was one."""
        base, runs = self.version(), self.runs()
        for tier in sorted({r.tier for r in runs}):
            full = [r for r in runs if r.tier == tier]
            if len(full) < self.fanout:
                continue
            old = sorted(full, key=lambda r: r.first)[: self.fanout]
            rows = self.spark.read.schema(schema).parquet(*[f"{self.root}/{r.name}" for r in old])
            made = self.write_run(rows, min(r.first for r in old), max(r.last for r in old), -(-sum(r.size for r in old) // self.target))
            # a merge moves up at least one tier, so that merging ends
            made = Run(**asdict(made) | {"tier": max(tier + 1, made.tier)})
            self.commit([r for r in runs if r not in old] + [made], base)
            return True
        return False

    def compact(self, schema) -> int:
        while self.merge_once(schema):
            pass
        return self.version()

    def read(self, schema, version: int | None = None) -> DataFrame:
        """The rows of a version's runs (the last one's if none is named), with ``shard_run`` and ``shard_tier``."""
        runs = self.runs(version)
        run_col = free_name(schema.names, "shard_run")
        tier_col = free_name([*schema.names, run_col], "shard_tier")
        if not runs:
            return self.spark.createDataFrame([], schema).withColumns({run_col: F.lit("").cast("string"), tier_col: F.lit(0)})
        rows = self.spark.read.schema(schema).parquet(*[f"{self.root}/{r.name}" for r in runs])
        run = F.regexp_extract(F.col("_metadata.file_path"), "/(run-[^/]+)/", 1)
        tiers = F.create_map(*[F.lit(x) for r in runs for x in (r.name, r.tier)])
        return rows.select(*[F.col(f"`{c}`") for c in schema.names], run.alias(run_col)).withColumn(tier_col, F.element_at(tiers, F.col(run_col)))


def shard_arrivals(docs: DataFrame, root: str, arrivals: int = 8, key: str = "doc_id", fanout: int = FANOUT, target_bytes: int = TARGET_BYTES) -> ShardSet:
    """Store a table as ``arrivals`` batches (rows dealt by hash of ``key``), compacting as tiers fill.

    One pass deals the rows to a folder for each batch; the folders then arrive one after the other by
    rename, each its own version.
    """
    shards = ShardSet(docs.sparkSession, root, fanout, target_bytes)
    slot, dealt = free_name(docs.columns, "arrival"), f"dealt-{uuid.uuid4().hex[:8]}"
    docs.withColumn(slot, F.pmod(F.xxhash64(key), F.lit(arrivals)).cast("int")).write.partitionBy(slot).parquet(f"{shards.root}/{dealt}")
    for k in range(arrivals):
        folder = f"{dealt}/{slot}={k}"
        if shards.fs.exists(shards.path(folder)):
            shards.adopt(folder, docs.schema)
            shards.compact(docs.schema)
    shards.fs.delete(shards.path(dealt), True)
    return shards
