"""Cross-site boilerplate lines by distinct-site spread.

For each line (hash of the line without blanks at its ends) a HyperLogLog sketch of the sites that have it is built
and merged by aggregation. Lines estimated well above MIN_SITES sites are boilerplate, lines well below are not, and lines
near the threshold get an exact distinct count. Boilerplate lines are then taken out of all documents.

Lines of one document count once. Sketches are merged map-side, so a line that every document has costs a task one
sketch; the verdict table is joined by broadcast if its counted size allows, else by hash with runtime skew splitting. What is
to be cut from a text is a sorted array of line hashes that its lines are looked up in by halving, so a text of n lines costs n log n.

Defined cases: null text is empty; empty lines are kept and never counted; a null site is one more site; repeated rows
are treated alike; columns pass unchanged except the text; where a column is called like one of the two counts, the count's name
gets an underscore; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, free_name, materialize, small, text_of

#: Sites that make a line boilerplate; the sketch's size (2**12 slots, 1.6 % error) and the width of the exact band.
MIN_SITES, LOG_SLOTS, NEAR = 8, 12, 0.25
BLANKS = " \t\r"


def normal(line: Column) -> Column:
    return F.btrim(line, F.lit(BLANKS))


def line_hashes(text: Column) -> Column:
    """Distinct hashes of the non-empty lines."""
    lines = F.filter(F.transform(F.split(text, "\n"), normal), lambda x: x != "")
    return F.array_distinct(F.transform(lines, lambda x: F.xxhash64(x)))


def boilerplate(docs: DataFrame, site: Column, text_col: str = "text", min_sites: int = MIN_SITES) -> DataFrame:
    """-> ``line`` (hash) of the lines on at least ``min_sites`` distinct sites."""
    each = docs.select(F.coalesce(site.cast("string"), F.lit("\0null")).alias("site"), F.explode(line_hashes(text_of(text_col))).alias("line"))
    sketches = each.groupBy("line").agg(F.hll_sketch_agg("site", F.lit(LOG_SLOTS)).alias("sketch"), F.count("*").alias("n")).where(F.col("n") >= min_sites)
    rated = materialize(sketches.select("line", F.hll_sketch_estimate("sketch").alias("sites")), "spread")
    low, high = min_sites * (1 - NEAR), min_sites * (1 + NEAR) + 1
    sure = rated.where(F.col("sites") > high).select("line")
    near = rated.where(F.col("sites").between(low, high)).select("line")
    exact = each.join(small(near, 16), "line").distinct().groupBy("line").count().where(F.col("count") >= min_sites).select("line")
    return sure.union(exact)


def stands_in(found: Column, x: Column) -> Column:
    """Whether ``x`` is in the sorted array: by halving, or at sight in a short one."""
    bits = F.length(F.bin(F.size(found).cast("long")))
    steps = F.reverse(F.sequence(F.lit(0), bits - 1))

    def step(at: Column, b: Column) -> Column:
        on = at + F.pow(F.lit(2), b).cast("int")
        return F.when((on <= F.size(found)) & (F.get(found, on - 1) <= x), on).otherwise(at)

    place = F.aggregate(steps, F.lit(0), step)
    return F.when(F.size(found) <= 16, F.array_contains(found, x)).otherwise(F.coalesce(F.get(found, place - 1) == x, F.lit(False)))


def without_boilerplate(docs: DataFrame, site: Column, text_col: str = "text", min_sites: int = MIN_SITES, lines_col: str = "n_lines", removed_col: str = "n_removed") -> DataFrame:
    """``docs`` with boilerplate lines cut from the text, and the numbers of non-empty lines before and of those cut."""
    bad = materialize(boilerplate(docs, site, text_col, min_sites), "boilerplate")
    text = text_of(text_col)
    own = {"key": F.xxhash64(text), "digest": F.md5(text)}
    names = {x: free_name(docs.columns, x) for x in (*own, "cut")}
    each = docs.select(F.xxhash64(text).alias("key"), F.md5(text).alias("digest"), F.explode(line_hashes(text)).alias("line"))
    hit = materialize(each.join(small(bad, 16), "line").groupBy("key", "digest").agg(F.sort_array(F.collect_set("line")).alias("cut")), "cut")
    size = hit.agg(F.coalesce(F.sum(F.size("cut") * 8 + 64), F.lit(0))).first()[0]
    hit = hit.select(*[F.col(x).alias(y) for x, y in names.items()])
    keyed = docs.withColumns({names[x]: c for x, c in own.items()})
    joined = keyed.join(F.broadcast(hit) if size <= BROADCAST_BYTES else hit, [names[x] for x in own], "left")
    lines, found = F.split(text, "\n"), F.col(names["cut"])
    is_cut = lambda x: (normal(x) != "") & stands_in(found, F.xxhash64(normal(x)))
    count = F.size(F.filter(lines, lambda x: normal(x) != "")).cast("long")
    removed = F.when(found.isNull(), 0).otherwise(F.size(F.filter(lines, is_cut))).cast("long")
    kept = F.when(found.isNull(), text).otherwise(F.array_join(F.filter(lines, lambda x: ~is_cut(x)), "\n"))
    others = [F.col(f"`{c}`") for c in docs.columns if c != text_col]
    lines_col = free_name(docs.columns, lines_col)
    removed_col = free_name([*docs.columns, lines_col], removed_col)
    return joined.select(*others, kept.alias(text_col), count.alias(lines_col), removed.alias(removed_col))
