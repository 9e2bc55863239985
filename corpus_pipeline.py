"""A corpus pipeline of five operators: toxic texts go, near copies go, benchmark leaks go, sources are mixed, shards written.

Every stage takes ``(spark, docs, sf_dir)`` and works on all rows that the one before has kept.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tilerank.llm import decontaminate, mixing, sharding, simhash_neardup, toxicity
from tilerank.llm.common import fresh_path, materialize

SHARES = {"sound": 0.9, "junk": 0.1}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.reject(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash_neardup.near_dedup(docs, shingle=5, least=0.8)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    domains = mixing.labelled_domains(table(spark, sf_dir, "labels")).where("domain <> 'toxic'")
    rates, _, _ = mixing.mix(docs, domains, SHARES)
    return mixing.resample(docs, rates)


def write_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    shards = sharding.shard_arrivals(docs, fresh_path(spark, "shards"), arrivals=6, target_bytes=32 << 20)
    return shards.read(docs.schema)


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash near-dedup", drop_near_copies),
    ("benchmark decontamination", drop_leaks),
    ("mixing", mix_sources),
    ("sharding", write_shards),
]

#: A learned score, fingerprints and alignment have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
