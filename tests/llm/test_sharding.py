from collections import Counter

import pytest
from pyspark.sql import functions as F

from tilerank.llm import registry, sharding
from tilerank.llm.common import fresh_path


def test_appends_merge_by_tiers_and_keep_every_row(spark):
    rows = [(i, None if i % 7 == 0 else "t" * (i % 50), i % 3) for i in range(400)] + [(5, "same", 1)] * 3
    df = spark.createDataFrame(rows, "doc_id bigint, text string, shard_run int")
    shards = sharding.ShardSet(spark, fresh_path(spark, "s"), fanout=3, small_bytes=1)
    assert shards.runs() == [] and shards.read(df.schema).count() == 0
    sizes = []
    for k in range(9):
        before = shards.version()
        shards.append(df.where(f"pmod(doc_id, 9) = {k}"))
        assert shards.version() == before + 1
        shards.compact(df.schema)
        sizes.append(len(shards.runs()))
        assert all(n < 3 for n in Counter(r.tier for r in shards.runs()).values())
    assert sum(r.rows for r in shards.runs()) == len(rows) and max(sizes) < 9
    got = shards.read(df.schema)
    assert got.columns == ["doc_id", "text", "shard_run", "shard_run_", "shard_tier"]
    assert Counter((r.doc_id, r.text, r.shard_run) for r in got.collect()) == Counter(rows)
    assert {r.shard_run_ for r in got.select("shard_run_").distinct().collect()} == {r.name for r in shards.runs()}
    v = shards.version()
    assert shards.append(df.limit(0)) == v == shards.version()


def test_a_version_is_committed_once(spark):
    shards = sharding.ShardSet(spark, fresh_path(spark, "s"))
    shards.append(spark.range(3))
    other = sharding.ShardSet(spark, shards.root)
    runs = other.runs()
    shards.commit(runs, 1)
    with pytest.raises(RuntimeError):
        other.commit([], 1)
    assert other.runs() == runs == other.runs(1)


def test_query_keeps_every_document(spark, sf):
    rows = registry.op6_sharding(spark, sf).collect()
    want = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    assert len(rows) == len(want) and {r.doc_id for r in rows} == set(want)
    assert all(r.text_chars == len(want[r.doc_id] or "") for r in rows)


def test_versions_stay_readable_until_they_expire(spark):
    df = spark.range(90).toDF("doc_id").withColumn("text", F.lit("x" * 100_000)).withColumn("dealt", F.col("doc_id") % 9)
    shards = sharding.ShardSet(spark, fresh_path(spark, "s"), fanout=3, small_bytes=1)
    want = {}
    for k in range(9):
        shards.append(df.where(f"dealt = {k}"))
        shards.compact(df.schema)
        want[shards.version()] = 10 * (k + 1)
    for version, n in want.items():
        assert shards.read(df.schema, version).count() == n
    assert shards.expire(keep=2) == []  # too young to go
    gone = shards.expire(keep=1, older_s=0.0)
    assert gone and shards.versions() == [shards.version()] and shards.read(df.schema).count() == 90
    assert {r.name for r in shards.runs()}.isdisjoint(gone)


def test_arrivals_of_odd_rows_and_names(spark):
    rows = [(None, None, 1), (None, None, 1), (1, "", 2), (2, "t" * 3_000_000, 3), (2, "u", 3)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, arrival__ int").withColumn("shard_tier", F.lit("x")).withColumn("arrival", F.lit(1))
    shards = sharding.shard_arrivals(df, fresh_path(spark, "s"), 3)
    got = shards.read(df.schema)
    assert Counter(tuple(r) for r in got.select(*df.columns).collect()) == Counter((*r, "x", 1) for r in rows)
    assert sharding.shard_arrivals(df.limit(0), fresh_path(spark, "s"), 3).read(df.schema).count() == 0
