"""Helpers shared by the text operators: shared-folder tables, checked broadcasts, components."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side is broadcast only if its measured size is within this bound; beyond it the join shuffles.
BROADCAST_BYTES = 64 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors and the driver see: ``spark.checkpoint.dir`` of the session.

    Only where that is unset and the master is local (tests), a temporary folder is made and set.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not found:
        found = getattr(shared_dir, "own", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        found = shared_dir.own = tempfile.mkdtemp(prefix="shared-")
        atexit.register(shutil.rmtree, found, ignore_errors=True)
    return found.rstrip("/")


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: lineage ends there and survives lost executors."""
    spark = df.sparkSession
    path = fresh_path(spark, label)
    df.write.parquet(path)
    table = spark.read.schema(df.schema).parquet(path)
    table.table_path = path
    return table


def release(*tables: DataFrame | None) -> None:
    """Remove materialized tables that no plan reads any more."""
    for t in tables:
        path = None if t is None else t.__dict__.pop("table_path", None)
        if path:
            spark = t.sparkSession
            p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def free_name(taken: list[str], name: str) -> str:
    """``name``, with underscores until no column is called so (Spark's names ignore case)."""
    used = {c.lower() for c in taken}
    while name.lower() in used:
        name += "_"
    return name


def small(df: DataFrame, row_bytes: int, limit: int = BROADCAST_BYTES) -> DataFrame:
    """Mark a materialized side for broadcast if its counted rows fit ``limit`` bytes; else leave it to shuffle."""
    return F.broadcast(df) if df.count() * row_bytes <= limit else df


def text_of(column: str | Column = "text") -> Column:
    """The text with null as empty."""
    c = F.col(column) if isinstance(column, str) else column
    return F.coalesce(c, F.lit(""))


#: A key is hot if it has more than this share of the rows; there are at most 1 / HOT_SHARE such keys.
HOT_SHARE = 1e-3


def look_up(rows: DataFrame, table: DataFrame, key: str, count: str, total: int, how: str = "inner") -> DataFrame:
    """``rows`` joined with ``table`` (one row a key, ``count`` rows of ``rows`` have it, ``total`` in all); ``count`` is left out.

    The keys that hold more than HOT_SHARE of the rows, so 1 / HOT_SHARE of them at most, are joined by broadcast; the rows of all others by hash, the
    hot ones' rows dealt out evenly.
    """
    values = [c for c in table.columns if c not in (key, count)]
    hot, spread, cold = (free_name([*rows.columns, *table.columns], x) for x in ("hot", "spread", "cold"))
    bound = max(1000, int(total * HOT_SHARE))
    held = F.struct(F.lit(1).alias("there"), *values)
    top = table.where(F.col(count) > bound).select(key, held.alias(hot))
    rest = table.where(F.col(count) <= bound).select(key, F.lit(0).cast("long").alias(spread), held.alias(cold))
    others = [c for c in rows.columns if c != key] or [key]
    both = rows.join(F.broadcast(top), key, "left")
    both = both.withColumn(spread, F.when(F.col(hot).isNotNull(), F.xxhash64(*others)).otherwise(F.lit(0)))
    both = both.join(rest, [key, spread], "left")
    found = F.coalesce(hot, cold)
    if how == "inner":
        both = both.where(found.isNotNull())
    return both.select(*[F.col(c) for c in rows.columns], *[found[v].alias(v) for v in values])


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """Connected components of a link table -> ``node``, ``component`` (smallest reachable node).

    Alternates two star contractions. Each round groups by node with map-side minima and joins them back, by broadcast as long as
    their counted size allows and then by ``look_up``, so that a hub's neighbours never meet in one task. A round is a table in the
    shared folder; that of the round before goes.
    Nodes without links don't appear; self links and nulls are ignored.
    """
    old = materialize(
        edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct(), "links"
    )
    mark, n = None, old.count()
    for _ in range(max_rounds):
        both = old.select("u", "v").union(old.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m"), F.count(F.when(F.col("v") > F.col("u"), 1)).alias("n"))
        least = least.select("u", F.least("u", "m").alias("m"), "n")
        few = 2 * n * 24 <= BROADCAST_BYTES
        large = (both.where("v > u").join(F.broadcast(least), "u") if few else look_up(both.where("v > u"), least, "u", "n", n)).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
        small_star = large.join(F.broadcast(least), "u") if few else look_up(large, least, "u", "n", n)
        new = (
            small_star.select(F.col("v").alias("u"), F.col("m").alias("v"))
            .where("u <> v")
            .union(least.select("u", F.col("m").alias("v")))
            .distinct()
        )
        before, old = old, materialize(new, "links")
        release(before)
        n, total = old.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        if (n, total) == mark:
            break
        mark = (n, total)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return old.select(F.col("u").alias("node"), F.col("v").alias("component")).union(
        old.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )
