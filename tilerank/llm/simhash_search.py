"""Document fingerprints: weighted SimHash, edits by the next document, and permuted block tables.

Only DataFrame and SQL functions. A term is a word between ASCII white space in lower case; its weight is
its length in bytes less three, from 1 to 12, so that long, rare words outvote the frequent short
ones. Each term's XXH64 votes with its weight for every bit, for 1 or against it. Two bit
counters share one 64-bit sum, so 32 sums hold the 64 votes of a text, in whole-stage code.

Defined cases: null text is empty; a text without terms has fingerprint zero; repeated rows come
back as often as they stand; rows of one id follow each other by text; null ids come first in the
order of documents; a single document follows itself; extra columns are ignored.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import look_up, materialize, text_of

WHITE = "[ \\t\\n\\x0B\\f\\r]+"
PAIR = 0x0000000100000001
#: Rows of a bucket of consecutive ids; buckets of buckets, and buckets in each of those, at most (a million buckets in all; they grow beyond).
BUCKET_ROWS, MOST_CUTS = 2000, 1000


def terms(text: Column) -> Column:
    return F.split(F.lower(text), WHITE)


def weight(term: Column) -> Column:
    return F.greatest(F.lit(1), F.least(F.lit(12), F.octet_length(term) - 3)).cast("long")


def vote(df: DataFrame, keys: list[str], text: str, out: str = "fp") -> DataFrame:
    """Group the terms of ``text`` by ``keys`` -> ``keys``, ``out``: bits on which more weight votes 1 than 0.

    Every key comes back: the empty term of an empty text has weight zero.
    """
    t = df.select(*keys, F.explode(terms(F.col(text))).alias("t"))
    t = t.select(*keys, F.xxhash64("t").alias("h"), F.when(F.col("t") == "", 0).otherwise(weight(F.col("t"))).cast("long").alias("w"))
    lanes = [F.sum(F.col("w") * F.expr(f"shiftrightunsigned(h, {j}) & {PAIR}L")).alias(f"s{j}") for j in range(32)]
    votes = t.groupBy(*keys).agg(F.sum("w").alias("w"), *lanes)
    low = " | ".join(f"shiftleft(bigint(2 * (s{j} & 4294967295L) > w), {j})" for j in range(32))
    high = " | ".join(f"shiftleft(bigint(2 * shiftrightunsigned(s{j}, 32) > w), {32 + j})" for j in range(32))
    return votes.select(*keys, F.expr(f"({low}) | ({high})").alias(out))


def likeness(a: str, b: str) -> Column:
    """Share of equal bits."""
    return 1 - F.bit_count(F.col(a).bitwiseXOR(F.col(b))) / F.lit(64.0)


def ordered_buckets(docs: DataFrame, id_col: str, rows: int = BUCKET_ROWS) -> DataFrame:
    """Add ``bucket`` (consecutive ranges of ids) and ``guest``: the first row of each range comes
    once more, as a guest at the end of the range before it; that of the first range in the last.

    Ranges start at ids that the table has, so a window over a bucket sees each row's successor and no window spans the table.
    They are quantiles in two levels: up to MOST_CUTS quantiles of all ids, which travel in the plan, and up to as many of the ids
    between two of those, aggregated by outer range into a broadcast table of at most MOST_CUTS ** 2 numbers.
    """
    size = docs.agg(F.count("*").alias("n"), F.count(id_col).alias("ids"), F.min(id_col).alias("first")).first()
    n = max(1, size["ids"] // rows)
    each = min(MOST_CUTS, max(1, round(n**0.5)))
    wide = min(MOST_CUTS, -(-n // each))
    opens = F.col(id_col).isNull() if size["ids"] < size["n"] else F.col(id_col) == F.lit(size["first"])
    if n == 1:
        placed = docs.withColumns({"own": F.lit(0), "leads": F.lit(False)})
        last = 0
    else:
        tops = docs.agg(F.percentile_approx(id_col, [i / wide for i in range(1, wide)], max(10_000, 4 * wide))).first()[0] if wide > 1 else []
        tops = sorted({t for t in tops if t > size["first"]})
        outer = F.size(F.filter(F.array(*[F.lit(t) for t in tops]).cast("array<bigint>"), lambda c: c <= F.col(id_col))) if tops else F.lit(0)
        outer = F.when(F.col(id_col).isNull(), 0).otherwise(outer)
        cuts = docs.where(F.col(id_col).isNotNull()).select(outer.alias("outer"), F.col(id_col).cast("long").alias("i")).groupBy("outer")
        cuts = cuts.agg(F.min("i").alias("least"), F.percentile_approx("i", [i / each for i in range(1, each)] or [0.5], max(10_000, 4 * each)).alias("cuts"))
        # inside an outer range after the first, its least id opens a bucket too
        cuts = cuts.select("outer", F.array_sort(F.array_distinct(F.concat(F.when(F.col("outer") > 0, F.array("least")).otherwise(F.array().cast("array<bigint>")), F.filter("cuts", lambda c: c > F.col("least"))))).alias("cuts"))
        cuts = materialize(cuts, "cuts")
        sizes = {r["outer"]: r["size"] for r in cuts.select("outer", F.size("cuts").alias("size")).collect()}  # MOST_CUTS rows at most
        base, before = [], 0
        for o in range(len(tops) + 1):
            base.append(before)
            before += sizes.get(o, 0)
        last = before
        inner = F.size(F.filter("cuts", lambda c: c <= F.col(id_col)))
        own = F.when(F.col(id_col).isNull(), 0).otherwise(F.get(F.array(*[F.lit(x) for x in base]), F.col("outer")) + inner)
        placed = docs.withColumn("outer", outer).join(F.broadcast(cuts), "outer", "left")
        placed = placed.withColumns({"own": own.cast("int"), "leads": F.coalesce(F.array_contains("cuts", F.col(id_col)), F.lit(False))})
    places = F.array(
        F.struct(F.col("own").alias("bucket"), F.lit(False).alias("guest")),
        F.when(opens, F.struct(F.lit(last).alias("bucket"), F.lit(True).alias("guest"))).when(
            F.col("leads"), F.struct((F.col("own") - 1).alias("bucket"), F.lit(True).alias("guest"))
        ),
    )
    placed = placed.withColumn("at", F.explode(F.filter(places, lambda p: p.isNotNull())))
    return placed.select(*docs.columns, "at.bucket", "at.guest")


def fingerprint_edits(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """-> ``id_col``, ``n_chars``, ``edited_sha256``, ``fp``, ``edited_fp``, ``next_fp``.

    The edited text is the text whose last quarter (rounded down) gives way to as much of the next
    document's beginning. The text is shuffled once, by ranges of ids; votes and successors stay in place.
    """
    placed = ordered_buckets(docs.select(F.col(id_col), text_of(text_col).alias("text")), id_col)
    order = Window.partitionBy("bucket").orderBy("guest", F.col(id_col).asc_nulls_first(), "text")
    n = F.char_length("text")
    quarter = F.floor(n / 4).cast("int")
    rows = placed.repartition("bucket").select(
        id_col, "bucket", "guest", "text", n.cast("long").alias("n_chars"), F.row_number().over(order).alias("rn"), F.lead("text").over(order).alias("next")
    )
    edited = F.concat(F.substring("text", F.lit(1), n - quarter), F.substring("next", F.lit(1), quarter))
    rows = rows.withColumn("edited", F.when(~F.col("guest"), edited))
    both = rows.select(
        "bucket", "rn", id_col, "guest", "n_chars",
        F.sha2("edited", 256).alias("edited_sha256"),
        F.explode(F.filter(F.array(F.struct(F.lit(0).alias("kind"), F.col("text").alias("body")), F.when(~F.col("guest"), F.struct(F.lit(1).alias("kind"), F.col("edited").alias("body")))), lambda p: p.isNotNull())).alias("p"),
    ).select("bucket", "rn", id_col, "guest", "n_chars", "edited_sha256", "p.kind", "p.body")
    keys = ["bucket", "rn", id_col, "guest", "n_chars", "edited_sha256", "kind"]
    votes = vote(both, keys, "body")
    one = votes.groupBy(*keys[:-1]).agg(F.max(F.when(F.col("kind") == 0, F.col("fp"))).alias("fp"), F.max(F.when(F.col("kind") == 1, F.col("fp"))).alias("edited_fp"))
    follow = Window.partitionBy("bucket").orderBy("rn")
    return one.withColumn("next_fp", F.lead("fp").over(follow)).where("not guest").select(id_col, "n_chars", "edited_sha256", "fp", "edited_fp", "next_fp")


def block_masks(blocks: int) -> list[int]:
    """64 bits cut into runs as even as can be."""
    ends = [64 * i // blocks for i in range(blocks + 1)]
    return [(1 << ends[i + 1]) - (1 << ends[i]) for i in range(blocks)]


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def permuted_tables(fps: DataFrame, blocks: int = 6, radius: int = 3, fp: str = "fp") -> DataFrame:
    """Distinct fingerprints -> ``fp``, ``tab``, ``prefix``: a row for each choice of ``blocks - radius`` whole blocks.

    ``tab`` is the bit set of the blocks that the prefix keeps. Two fingerprints within ``radius`` bits agree on
    some choice.
    """
    if not 0 <= radius < blocks:
        raise ValueError("needs more blocks than bits of radius")
    masks = block_masks(blocks)
    kept = [(sum(1 << b for b in c), signed(sum(masks[b] for b in c))) for c in combinations(range(blocks), blocks - radius)]
    rows = F.array(*[F.struct(F.lit(t).alias("tab"), F.col(fp).bitwiseAND(F.lit(m).cast("long")).alias("prefix")) for t, m in kept])
    return fps.select(F.col(fp).alias("fp"), F.explode(rows).alias("r")).select("fp", "r.tab", "r.prefix")


def within_radius(queries: DataFrame, base: DataFrame, blocks: int = 6, radius: int = 3) -> DataFrame:
    """Distinct fingerprints ``fp`` on both sides -> ``x`` (query), ``y`` (base), ``bits``: all pairs within ``radius``, itself too.

    A pair meets in every table whose blocks it agrees on and is reported by the first of them.
    """
    a = permuted_tables(queries, blocks, radius).select("tab", "prefix", F.col("fp").alias("x"))
    b = permuted_tables(base, blocks, radius).select("tab", "prefix", F.col("fp").alias("y"))
    agree = " + ".join(f"if((x ^ y) & {signed(m)}L = 0, {1 << i}, 0)" for i, m in enumerate(block_masks(blocks)))
    first, rest = "0", f"({agree})"
    for _ in range(blocks - radius):
        first, rest = f"{first} | ({rest} & -{rest})", f"({rest} & ({rest} - 1))"
    met = a.join(b, ["tab", "prefix"]).where(f"bit_count(x ^ y) <= {radius}").where(f"tab = ({first})")
    return met.select("x", "y", F.expr("bit_count(x ^ y)").alias("bits"))


def search_counts(found: DataFrame, radius: int = 3) -> DataFrame:
    """Add ``n_near``: other documents whose fingerprint is within ``radius`` bits of the row's."""
    nodes = materialize(found.groupBy("fp").agg(F.count("*").alias("copies")), "fingerprints")
    near = within_radius(nodes.select("fp"), nodes.select("fp"), radius=radius).where("x <> y")
    near = near.join(nodes.toDF("y", "copies"), "y").groupBy("x").agg(F.sum("copies").alias("others"))
    counts = nodes.join(near, nodes["fp"] == near["x"], "left").where("copies > 1 or others is not null")
    counts = materialize(counts.select("fp", "copies", (F.col("copies") - 1 + F.coalesce("others", F.lit(0))).alias("n_near")), "counts")
    return look_up(found, counts, "fp", "copies", found.count(), "left").withColumn("n_near", F.coalesce("n_near", F.lit(0)).cast("long"))
