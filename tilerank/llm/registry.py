"""The queries of the text operators over whole tables, and SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, licenses, linededup, mixing, secrets, sharding, simhash_neardup, simhash_search, toxicity, warc
from .common import fresh_path, materialize

QUERIES: dict = {}
ORACLES: dict = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@query
def op10_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash_neardup.simhash_components(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def hex64(column: str):
    return F.lower(F.lpad(F.hex(column), 16, "0"))


@query
def op9_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = materialize(simhash_search.fingerprint_edits(table(spark, sf_dir, "documents")), "edits")
    return simhash_search.search_counts(found).select(
        "doc_id",
        "n_chars",
        "edited_sha256",
        hex64("fp").alias("fingerprint"),
        hex64("edited_fp").alias("edited_fingerprint"),
        simhash_search.likeness("fp", "edited_fp").alias("near_edited"),
        simhash_search.likeness("fp", "next_fp").alias("near_next"),
        "n_near",
    )


@query
def op8_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = decontaminate.leaks(docs, table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", (F.size("leaked_items") > 0).alias("contaminated"), F.col("leaked_items").alias("item_ids"))


@query
def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    # only the id and the score leave the Python pass
    scored = toxicity.with_scores(docs, model).select("doc_id", "score")
    return scored.select("doc_id", toxicity.held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


#: Arrivals and target file size of the sharding query.
ARRIVALS, SHARD_BYTES = 6, 32 << 20


@query
def op6_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    shards = sharding.shard_arrivals(docs, fresh_path(spark, "shards"), ARRIVALS, target_bytes=SHARD_BYTES)
    # read back from the live version; how runs are named and tiered depends on bytes, so the rows carry contents only
    return shards.read(docs.schema).select("doc_id", "lang", "source", F.char_length("text").cast("long").alias("text_chars"), F.md5("text").alias("text_md5"))


ORACLES["op6_sharding"] = "SELECT doc_id, lang, source, CAST(length(text) AS BIGINT) AS text_chars, md5(text) AS text_md5 FROM documents"


#: Target shares of tokens.
SHARES = {"sound": 0.85, "junk": 0.12, "toxic": 0.03}


@query
def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    rates, domains, _ = mixing.mix(docs, mixing.labelled_domains(table(spark, sf_dir, "labels")), SHARES)
    shares = [F.get("posterior", F.lit(i)).alias(f"p_{d}") for i, d in enumerate(domains)]
    return rates.select("doc_id", "tokens", *shares, "rate", mixing.copies(F.col("rate"), F.col("doc_id")).alias("copies"))


@query
def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A document's source is its owner; the owner's documents of one language are a repository."""
    docs = table(spark, sf_dir, "documents")
    return secrets.scan(docs, F.concat_ws("/", "source", "lang"), F.col("source"))


@query
def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    clean = linededup.without_boilerplate(docs, F.col("source"))
    return clean.select("doc_id", "n_lines", "n_removed", F.char_length("text").cast("long").alias("clean_chars"), F.md5("text").alias("clean_md5"))


ORACLES["op3_line_dedup"] = r"""
WITH docs AS (
  SELECT doc_id, coalesce(source, chr(1)) AS site, coalesce(text, '') AS body FROM documents
), lines AS (
  SELECT doc_id, site, unnest(list_transform(string_split(body, chr(10)), lambda x: trim(x, ' ' || chr(9) || chr(13)))) AS line FROM docs
), bad AS (
  SELECT line FROM lines WHERE line <> '' GROUP BY line HAVING count(DISTINCT site) >= 8
), bad_list AS (
  SELECT coalesce(list(line), []) AS xs FROM bad
), split AS (
  SELECT doc_id, list_transform(string_split(body, chr(10)), lambda x: {'raw': x, 'line': trim(x, ' ' || chr(9) || chr(13))}) AS parts FROM docs
), marked AS (
  SELECT doc_id, parts, list_filter(parts, lambda p: p.line = '' OR NOT list_contains(xs, p.line)) AS kept FROM split, bad_list
)
SELECT doc_id,
       CAST(len(list_filter(parts, lambda p: p.line <> '')) AS BIGINT) AS n_lines,
       CAST(len(parts) - len(kept) AS BIGINT) AS n_removed,
       CAST(length(array_to_string(list_transform(kept, lambda p: p.raw), chr(10))) AS BIGINT) AS clean_chars,
       md5(array_to_string(list_transform(kept, lambda p: p.raw), chr(10))) AS clean_md5
FROM marked
"""


@query
def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = licenses.license_blocks(table(spark, sf_dir, "documents"))
    names = F.array_distinct(F.transform("blocks", lambda b: b["license"]))
    exact = F.size(F.filter("blocks", lambda b: b["exact"])).cast("long")
    return found.select("doc_id", F.size("blocks").cast("long").alias("n_blocks"), exact.alias("n_exact"), F.array_join(F.array_sort(names), ",").alias("licenses"), F.to_json("blocks").alias("blocks"))


@query
def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_and_read(table(spark, sf_dir, "pages").select("page_id", "url", "html"))


ORACLES["op7_warc"] = """
WITH raw AS (SELECT page_id, coalesce(html, '') AS body FROM pages),
p AS (SELECT page_id, CAST(octet_length(encode(body)) AS BIGINT) AS n, sha1(body) AS hex, max(page_id) OVER (PARTITION BY body) AS last FROM raw)
SELECT page_id, n AS payload_bytes,
  array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
    CAST((CAST('0x' || substr(hex, CAST(i // 4 * 5 + 1 AS INTEGER), 5) AS BIGINT) >> CAST(15 - i % 4 * 5 AS BIGINT)) & 31 AS INTEGER) + 1, 1)), '') AS payload_digest,
  CASE WHEN page_id = last THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> last THEN last END AS refers_to
FROM p
"""
