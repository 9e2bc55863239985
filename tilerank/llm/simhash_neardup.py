"""SimHash near-duplicates found by anchor-point covering.

A fingerprint half of 31 bits is a point of a space that the perfect Hamming code covers with
radius 1: every point has one codeword within one bit (its *home* anchor). Two fingerprints that
differ in at most 3 of 64 bits differ in at most 1 bit of one half, so there one lies within
1 + 1 = 2 bits of the other's home. Every fingerprint is therefore sent to all anchors within
2 bits (16 of 2**26 a half) and compared there with those at home. Anchors are computed from parity
bits by column arithmetic; nothing is broadcast and no group is gathered.

Cost: 32 short rows for each distinct fingerprint. Equal fingerprints are one node, so groups of
copies add nothing, and Spark may split a crowded anchor (a plain equi-join).

Defined cases: null text is empty; a text without words has fingerprint zero and links like any
other; repeated rows come back as often as they stand; rows whose doc_id is null are returned with
their fingerprint and the component of the fingerprint's smallest non-null doc_id; an empty table
gives an empty result; columns other than the id and the text are ignored.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, look_up, materialize, release, small

LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
#: Bit positions 1..31 whose number has bit k set, as a mask over bits 0..30.
PARITY = [sum(1 << (i - 1) for i in range(1, 32) if i >> k & 1) for k in range(5)]
HALF = 0x7FFFFFFF
#: Columns of a way from the members of one band value to those of another.
WAY = ["band", "v", "w"]
#: 64-bit words of a parity sketch.
SKETCH = 8
#: Bands settled one group after the other: the first ones, then the rest.
BAND_GROUPS = ((0, 4), (4, 12))


def words(text: str | None) -> list[bytes]:
    """Words between ASCII white space, A-Z lowered, as UTF-8."""
    return (text or "").encode("utf-8", "surrogatepass").translate(LOWER).split()


def shingle_hashes(w: list[bytes], k: int, seed: int = 42) -> list[int]:
    """XXH64 of each run of k words joined by a space; of the whole sequence if it is shorter."""
    if not w:
        return []
    line = memoryview(b" ".join(w))
    if len(w) <= k:
        return [xxhash.xxh64_intdigest(line, seed)]
    ends = np.cumsum([len(x) + 1 for x in w])
    starts = [0, *ends[: len(w) - k].tolist()]
    h = xxhash.xxh64_intdigest
    return [h(line[a:b], seed) for a, b in zip(starts, (ends[k - 1 :] - 1).tolist(), strict=True)]


def majority(h: np.ndarray) -> np.ndarray:
    """(n, k) uint64 -> k uint64 whose bits are set in more than half of the rows.

    Eight bits are counted at a time in the byte lanes of 64-bit sums over 255 rows.
    """
    n, k = h.shape
    if not n:
        return np.zeros(k, np.uint64)
    if pad := -n % 255:
        h = np.concatenate([h, np.zeros((pad, k), np.uint64)])
    counts = np.zeros((k, 8, 8), np.int64)
    for j in range(8):
        lanes = ((h >> np.uint64(j)) & np.uint64(0x0101010101010101)).reshape(-1, 255, k).sum(1)
        counts[:, :, j] = lanes.astype("<u8").view(np.uint8).reshape(-1, k, 8).sum(0, dtype=np.int64)
    bits = (2 * counts > n).reshape(k, 64)
    return np.packbits(bits, axis=1, bitorder="little").view("<u8").ravel()


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """-> ``id_col``, ``fp`` (64 bits as a signed long): the unweighted SimHash of the shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = [
                majority(np.array(shingle_hashes(words(t.as_py()), shingle), np.uint64).reshape(-1, 1))[0]
                for t in batch.column(1)
            ]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(np.array(fps, np.uint64).view(np.int64))], names=[id_col, "fp"]
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, fp bigint")


def with_anchors(points: DataFrame, value: str, home: bool) -> DataFrame:
    """Add ``anchor``: the codeword at home of the 31-bit ``value``, or a row for each codeword within two bits."""
    syndrome = " + ".join(f"shiftleft(bit_count({value} & {m}L) & 1, {k})" for k, m in enumerate(PARITY))
    points = points.withColumn("s", F.expr(f"int({syndrome})"))
    flip = "shiftright(shiftleft(1L, {0}), 1)".format  # position 0 flips nothing
    if home:
        return points.withColumn("anchor", F.expr(f"{value} ^ {flip('s')}")).drop("s")
    return (
        points.withColumn("i", F.explode(F.expr("sequence(0, 31)")))
        .where("i < (i ^ s) or (s = 0 and i = 0)")
        .withColumn("anchor", F.expr(f"{value} ^ {flip('i')} ^ {flip('(i ^ s)')}"))
        .drop("s", "i")
    )


def hamming_links(nodes: DataFrame, fp: str = "fp", radius: int = 3) -> DataFrame:
    """Distinct fingerprints -> ``x``, ``y`` (x < y): all pairs that differ in at most ``radius`` bits (3 at most)."""
    if not 0 <= radius <= 3:
        raise ValueError("two covered halves find pairs within 3 bits")
    halves = nodes.select(F.col(fp).alias("f")).select(
        "f", F.explode(F.expr(f"array(struct(0 as half, f & {HALF}L as v), struct(1 as half, shiftrightunsigned(f, 32) & {HALF}L as v))")).alias("h")
    ).select("f", "h.half", "h.v")
    home = with_anchors(halves, "v", True).select("half", "anchor", F.col("f").alias("x"))
    visit = with_anchors(halves, "v", False).select("half", "anchor", F.col("f").alias("y"))
    # both sides shuffle: estimates don't know that a row of nodes becomes 32 visits, and a broadcast of those would be gathered on the driver
    return home.join(visit.hint("merge"), ["half", "anchor"]).where(f"x < y and bit_count(x ^ y) <= {radius}").select("x", "y").distinct()


def simhash_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, radius: int = 3) -> DataFrame:
    """-> ``id_col``, ``fp``, ``component_id`` (smallest id reachable over links of at most ``radius`` bits)."""
    fps = materialize(fingerprints(docs, id_col, text_col, shingle), "simhash")
    nodes = materialize(fps.groupBy("fp").agg(F.min(id_col).alias("rep"), F.count("*").alias("n")), "simhash")
    links = hamming_links(nodes, "fp", radius)
    reps = nodes.select("fp", "rep").where("rep is not null")
    edges = links.join(reps.toDF("x", "a"), "x").join(reps.toDF("y", "b"), "y").select("a", "b")
    linked = components(edges)
    found = nodes.join(linked, nodes["rep"] == linked["node"], "left").where("n > 1 or component is not null")
    found = found.select("fp", F.coalesce("component", "rep").alias("component"))
    return fps.join(found, "fp", "left").select(id_col, "fp", F.coalesce("component", id_col).alias("component_id"))


def wide_fingerprints(docs: DataFrame, id_col: str, text_col: str, shingle: int) -> DataFrame:
    """-> ``id_col``, ``key`` (128-bit digest of the lowered words), ``f`` (six SimHashes of the words), ``m``, ``o``.

    ``m`` is the number of distinct shingles and ``o`` has a bit for each of 64 * SKETCH hash classes: whether
    the class holds an odd number of them. Each shingle that only one of two texts has flips one bit, so
    sketches differ in no more bits than the sets differ in shingles.

    The votes are cast by the distinct words of five and more bytes (all words if there are none): an
    edit of one word then moves one vote, not ``shingle`` of them, and frequent short words don't
    make unrelated texts alike.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        digest = xxhash.xxh3_128_digest
        for batch in batches:
            keys, rows, sizes, odd = [], [], [], []
            for t in batch.column(1):
                w = words(t.as_py())
                g = np.unique(np.array(shingle_hashes(w, shingle), np.uint64))
                sizes.append(len(g))
                parity = np.bincount((g % np.uint64(64 * SKETCH)).astype(np.int64), minlength=64 * SKETCH) & 1
                odd.append(np.packbits(parity.astype(np.uint8)).view("<i8").tolist())
                keys.append(digest(b" ".join(w)))
                distinct = set(w)
                terms = [x for x in distinct if len(x) > 4] or list(distinct)
                raw = b"".join([digest(x, 42) + digest(x, 43) + digest(x, 44) for x in terms])
                rows.append(majority(np.frombuffer(raw, "<u8").reshape(-1, 6)).view(np.int64).tolist())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(keys, pa.binary()), pa.array(rows, pa.list_(pa.int64())), pa.array(sizes, pa.int32()), pa.array(odd, pa.list_(pa.int64()))],
                names=[id_col, "key", "f", "m", "o"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, key binary, f array<bigint>, m int, o array<bigint>")


def bands_of(nodes: DataFrame) -> DataFrame:
    """``rep``, ``f`` -> (``rep``, ``band``, ``v``), a row for each half of each fingerprint."""
    halves = f"array(struct(2 * i as band, v & {HALF}L as v), struct(2 * i + 1 as band, shiftrightunsigned(v, 32) & {HALF}L as v))"
    bands = nodes.select("rep", F.explode(F.expr(f"flatten(transform(f, (v, i) -> {halves}))")).alias("h"))
    return materialize(bands.select("rep", "h.band", "h.v"), "bands")


def value_components(bands: DataFrame, labels: DataFrame | None) -> DataFrame:
    """(``band``, ``v``, ``lo``, ``hi``): the least and the largest component of each band value's members."""
    return labelled(bands, labels).groupBy("band", "v").agg(F.min("c").alias("lo"), F.max("c").alias("hi"))


def same_values(nodes: DataFrame, bands: DataFrame, labels: DataFrame | None) -> tuple[DataFrame, DataFrame]:
    """Members of the band values that several components share, as ``members_at`` has them, and those values as pairs ``v``, ``w`` = ``v``.

    The members of one component alone make no rows, however many they are.
    """
    mixed = materialize(value_components(bands, labels).where("lo <> hi").select("band", "v", F.col("v").alias("w")), "values")
    return members_at(nodes, bands, mixed.select("band", "v")), mixed


def members_at(nodes: DataFrame, bands: DataFrame, values: DataFrame) -> DataFrame:
    """``band``, ``v``, ``rep``, ``m``, ``o``: the members of distinct band values, once each."""
    rows = bands.join(small(values, 16), ["band", "v"])
    return materialize(rows.join(nodes.select("rep", "m", "o"), "rep").select("band", "v", "rep", "m", "o"), "members")


def labelled(rows: DataFrame, labels: DataFrame | None, node: str = "rep") -> DataFrame:
    """Add ``c``, the component of the node: itself if it has no link."""
    if labels is None:
        return rows.withColumn("c", F.col(node))
    return rows.join(small(labels.toDF(node, "of"), 32), node, "left").withColumn("c", F.coalesce("of", node)).drop("of")


def component_sizes(labels: DataFrame | None) -> DataFrame | None:
    """``rep``, ``of``, ``of_n``: the component of each linked node, and how many nodes that has."""
    if labels is None:
        return None
    sizes = materialize(labels.groupBy("component").agg(F.count("*").alias("of_n")), "sizes")
    sized = materialize(labels.join(small(sizes, 24), "component").select(F.col("node").alias("rep"), F.col("component").alias("of"), "of_n"), "sized")
    release(sizes)
    return sized


def ranked(rows: DataFrame, sized: DataFrame | None) -> DataFrame:
    """Add ``c``, the component of ``rep``, and ``rank``: components in one order, the larger ones last."""
    if sized is None:
        return rows.withColumn("c", F.col("rep")).withColumn("rank", F.struct(F.lit(1).cast("long").alias("n"), "c"))
    rows = rows.join(small(sized, 40), "rep", "left").withColumn("c", F.coalesce("of", "rep"))
    return rows.withColumn("rank", F.struct(F.coalesce("of_n", F.lit(1).cast("long")).alias("n"), "c")).drop("of", "of_n")


def near_values(nodes: DataFrame, bands: DataFrame, labels: DataFrame | None) -> tuple[DataFrame, DataFrame]:
    """Pairs of band values ``v``, ``w`` (both ways) that are one bit apart and not both of one component alone, after their members (``members_at``).

    Values one bit apart are found at anchors; a value has 31 such neighbours at most. A cluster whose values are neighbours in many
    ways is one component by then, so its pairs of values make no rows. A member is one row however many neighbours its value has.
    """
    points = materialize(value_components(bands, labels), "points")
    home = with_anchors(points, "v", True)
    visit = with_anchors(points.toDF("band", "w", "least", "most"), "w", False)
    near = home.join(visit, ["band", "anchor"]).where("v < w and bit_count(v ^ w) <= 1 and least(lo, least) <> greatest(hi, most)")
    near = near.select("band", "v", "w").distinct()
    near = materialize(near.union(near.select("band", "w", "v")), "near")
    values = materialize(near.select("band", "v").distinct(), "values")
    out = members_at(nodes, bands, values)
    release(points, values)
    return out, near


def may_be_like(least: float) -> str:
    """Condition on ``m``, ``o`` and ``l.m``, ``l.o`` that holds for all sets whose Jaccard similarity is at least ``least``.

    Such sets of p and q shingles differ in at most (p + q) (1 - least) / (1 + least) of them, so their sketches do.
    """
    apart = " + ".join(f"bit_count(o[{i}] ^ l.o[{i}])" for i in range(SKETCH))
    return f"abs(m - l.m) <= (m + l.m) * {(1 - least) / (1 + least)!r}D + 1e-6D and {apart} <= (m + l.m) * {(1 - least) / (1 + least)!r}D + 1e-6D"


@dataclass
class Known:
    """What is settled so far: components (``node``, ``component``; None if there is no link), and the pairs compared."""

    labels: DataFrame | None = None
    tried: list[DataFrame] = field(default_factory=list)


def settle(members: DataFrame, confirm: Callable[[DataFrame], DataFrame], least: float, known: Known | None = None, leaders: int = 64, meet: DataFrame | None = None) -> Known:
    """Components of all pairs that meet and that ``confirm`` keeps, beside what is ``known``.

    ``members`` of a band value ``v`` meet those of ``w`` for each row (``band``, ``v``, ``w``) of ``meet``, which has both ways of a
    pair; without it, those of ``v`` itself. Components are in one order by size. In each round members of ``v`` lead if their component is below
    the last of ``w``: ``leaders`` of them (sixteen times as many in each further round) are compared with the members of other components at ``w``. A pair of values is
    settled once all that had to lead have led. Of two members in different components the lower one has led then, so no
    link is lost. Only those that lead are repeated for the pairs of their value, never the members of a cluster that they stand beside.
    Rows are made for pairs that pass ``may_be_like`` only; where members stay apart the comparisons themselves
    still grow with the square of their number.
    """
    known, led, own = known or Known(), [], []
    members = members.select("band", "v", "rep", "m", "o")
    if meet is None:
        meet = members.select("band", "v", F.col("v").alias("w")).distinct()
    while True:
        sized = component_sizes(known.labels)
        seen = materialize(ranked(members, sized), "seen")
        tops = seen.groupBy("band", F.col("v").alias("w")).agg(F.max("rank").alias("top"))
        ways = materialize(meet.join(tops, ["band", "w"]), "ways")
        own += [sized, seen, ways]
        fresh = seen.join(small(ways, 48), ["band", "v"]).where("rank < top")
        for x in led:
            fresh = fresh.join(x.select(*WAY, "l.rep"), [*WAY, "rep"], "left_anti")
        chosen = fresh.groupBy(*WAY, F.pmod(F.xxhash64("rep"), F.lit(leaders)).alias("salt")).agg(F.min(F.struct("rep", "c", "m", "o")).alias("l"), F.count("*").alias("k"))
        chosen = materialize(chosen.select(*WAY, "l", "k"), "leaders")
        led.append(chosen)
        if chosen.isEmpty():
            release(*own, *led)
            return known
        met = small(chosen, 192).drop("v", "k").join(seen.withColumnRenamed("v", "w"), ["band", "w"]).where((F.col("c") != F.col("l.c")) & F.expr(may_be_like(least)))
        pairs = met.select(F.least("rep", "l.rep").alias("a"), F.greatest("rep", "l.rep").alias("b")).distinct()
        for x in known.tried:
            pairs = pairs.join(x, ["a", "b"], "left_anti")
        pairs = materialize(pairs, "pairs")
        known.tried.append(pairs)
        if not pairs.isEmpty():
            links = confirm(pairs)
            links = links if "table_path" in links.__dict__ else materialize(links, "confirmed")
            if not links.isEmpty():
                before = known.labels
                known.labels = materialize(components(links if before is None else links.union(before.toDF("a", "b"))), "components")
                release(before)
            release(links)
        late = chosen.where("k > 1").select(*WAY)
        meet = materialize(late.union(late.select("band", F.col("w").alias("v"), F.col("v").alias("w"))).distinct(), "open")
        values = materialize(meet.select("band", "v").distinct(), "values")
        own += [meet, values]
        if values.isEmpty():
            release(*own, *led)
            return known
        members = seen.drop("c", "rank").join(small(values, 16), ["band", "v"], "left_semi")
        leaders *= 16


def shingle_sets(docs: DataFrame, id_col: str, text_col: str, shingle: int) -> DataFrame:
    """-> ``id_col``, ``g`` (sorted distinct shingle hashes, 8 bytes each)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [np.unique(np.array(shingle_hashes(words(t.as_py()), shingle), np.uint64)).tobytes() for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.binary())], names=[id_col, "g"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, g binary")


def jaccard_at_least(pairs: DataFrame, least: float) -> DataFrame:
    """``a``, ``b``, ``ga``, ``gb`` -> the pairs whose shingle sets are at least so similar."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("ga"), batch.column("gb"), strict=True):
                p, q = np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64)
                both = len(np.intersect1d(p, q, assume_unique=True))
                keep.append(both >= least * (len(p) + len(q) - both))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return pairs.select("a", "b", "ga", "gb").mapInArrow(run, pairs.select("a", "b").schema)


def near_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, least: float = 0.8) -> tuple[DataFrame, DataFrame]:
    """-> (``id_col``, ``rep``): a row for each row with an id, and the smallest id of equal lowered words; (``node``, ``component``) of
    linked representatives, the smallest of them.

    Links: wide SimHashes that agree on one of twelve bands, or differ in one bit of it, confirmed by the exact Jaccard similarity
    of ``shingle``-word sets, at least ``least``. Equal values are settled first, a group of bands after the other.
    """
    fps = materialize(wide_fingerprints(docs, id_col, text_col, shingle).where(F.col(id_col).isNotNull()), "wide")
    nodes = fps.groupBy("key").agg(F.min(id_col).alias("rep"), F.min_by(F.struct("f", "m", "o"), id_col).alias("x"), F.count("*").alias("n"))
    nodes = materialize(nodes.select("key", "rep", "n", "x.f", "x.m", "x.o"), "nodes")
    bands = bands_of(nodes)

    def confirm(pairs: DataFrame) -> DataFrame:
        wanted = materialize(pairs.select(F.col("a").alias(id_col)).union(pairs.select("b")).distinct(), "met")
        picked = docs.select(id_col, text_col).join(small(wanted, 16), id_col, "left_semi")
        # repeated rows of an id: the text that stands for it is the one that its fingerprint was taken from
        sets = materialize(shingle_sets(picked, id_col, text_col, shingle).groupBy(id_col).agg(F.min("g").alias("g")), "shingles")
        out = materialize(jaccard_at_least(pairs.join(sets.toDF("a", "ga"), "a").join(sets.toDF("b", "gb"), "b"), least), "alike")
        release(wanted, sets)
        return out

    known = Known()
    for lo, hi in BAND_GROUPS:
        own = bands.where((F.col("band") >= lo) & (F.col("band") < hi))
        members, meet = same_values(nodes, own, known.labels)
        known = settle(members, confirm, least, known, meet=meet)
        release(members, meet)
    members, meet = near_values(nodes, bands, known.labels)
    known = settle(members, confirm, least, known, meet=meet)
    copies = look_up(fps.select(id_col, "key"), nodes.select("key", "rep", "n"), "key", "n", fps.count()).select(id_col, "rep")
    copies = materialize(copies, "copies")
    release(fps, nodes, bands, members, meet, *known.tried)
    linked = known.labels
    if linked is None:
        linked = copies.select(F.col("rep").alias("node"), F.col("rep").alias("component")).limit(0)
    return copies, linked


def near_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, least: float = 0.8) -> DataFrame:
    """One document of each class of near copies (``near_classes``): the one with the smallest id stays.

    Columns pass unchanged. Rows with a null id stay; of repeated rows of one id one stays.
    """
    copies, linked = near_classes(docs, id_col, text_col, shingle, least)
    # ids that leave: copies of a text but the first, and representatives linked to a smaller one
    lost = copies.where(F.col(id_col) != F.col("rep")).select(id_col).union(linked.where("node <> component").select("node"))
    out = materialize(lost.distinct(), "lost")
    kept = docs.join(small(out, 16), id_col, "left_anti").select(*docs.columns)
    again = copies.groupBy(id_col).count().where("count > 1").select(id_col)
    if not again.isEmpty():
        again = small(materialize(again, "again"), 16)
        once = kept.join(again, id_col, "left_anti").select(*docs.columns)
        kept = once.union(kept.join(again, id_col, "left_semi").select(*docs.columns).dropDuplicates([id_col]))
    return kept
