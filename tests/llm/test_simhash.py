import hashlib
import re
from collections import Counter

import pytest
import xxhash
from pyspark.sql import functions as F

from tilerank.llm import common, registry, simhash_neardup, simhash_search

EDGE = [(1, "a b c d"), (2, None), (3, ""), (4, " \t\n"), (5, "a b c d"), (5, "a b c d"), (7, "Ä " * 3), (8, "x"), (None, "a b c d"), (9, "long word " * 5000)]
SCHEMA = "doc_id bigint, text string"


def brute_fp(text, k):
    w = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    runs = [" ".join(w[i : i + k]) for i in range(len(w) - k + 1)] if len(w) >= k else [" ".join(w)] if w else []
    h = [xxhash.xxh64_intdigest(r.encode(), 42) for r in runs]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(fps, radius):
    ids = sorted({i for i, _ in fps if i is not None})
    group = {f: min((i for i, g in fps if g == f and i is not None), default=None) for f in {f for _, f in fps}}
    up = {i: i for i in ids}

    def top(i):
        while up[i] != i:
            i = up[i]
        return i

    nodes = list(group)
    for n, x in enumerate(nodes):
        for y in nodes[:n]:
            if (x ^ y).bit_count() <= radius and group[x] is not None and group[y] is not None:
                a, b = sorted((top(group[x]), top(group[y])))
                up[b] = a
    return {f: None if g is None else top(g) for f, g in group.items()}


def test_components_against_brute_force(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    base = next(t for _, t in rows if len(t.split()) > 300)
    words = base.split()
    rows += [(10_000 + i, " ".join(w if j != 7 * i else "changed" for j, w in enumerate(words))) for i in range(20)] + EDGE
    got = registry.op10_simhash_near_dedup
    df = spark.createDataFrame(rows, SCHEMA)
    found = simhash_neardup.simhash_components(df).collect()
    fps = [(i, brute_fp(t, 3)) for i, t in rows]
    comp = brute_components(fps, 3)
    want = Counter((i, f, comp[f]) for i, f in fps)
    assert Counter((r.doc_id, r.fp % 2**64, r.component_id) for r in found) == want
    assert got(spark, sf).columns == ["doc_id", "fingerprint", "component_id"]
    assert simhash_neardup.simhash_components(df.limit(0)).count() == 0


def test_visits_of_anchors_are_not_broadcast(spark, tmp_path):
    nodes = spark.range(2000).select(F.xxhash64("id").alias("fp"))
    nodes.write.parquet(f"{tmp_path}/nodes")
    links = simhash_neardup.hamming_links(spark.read.parquet(f"{tmp_path}/nodes"))
    links.collect()
    plan = links._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Broadcast" not in plan


def test_hamming_links_are_exact(spark):
    import random

    rnd = random.Random(3)
    base = [rnd.getrandbits(64) for _ in range(40)] + [0, 2**64 - 1]
    fps = sorted({f ^ sum(1 << b for b in rnd.sample(range(64), rnd.randrange(5))) for f in base for _ in range(8)})
    df = spark.createDataFrame([(simhash_search.signed(f),) for f in fps], "fp bigint")
    want = {(x, y) for x in fps for y in fps if x < y and (x ^ y).bit_count() <= 3}
    unordered = lambda rows: {tuple(sorted((r.x % 2**64, r.y % 2**64))) for r in rows}
    assert unordered(simhash_neardup.hamming_links(df).collect()) == want
    met = simhash_search.within_radius(df, df).where("x <> y").collect()
    assert unordered(met) == want and len(met) == 2 * len(want)


def brute_vote(text):
    total, votes = 0, [0] * 64
    for t in re.split("[ \t\n\x0b\f\r]+", (text or "").lower()):
        w = 0 if not t else max(1, min(12, len(t.encode()) - 3))
        h = xxhash.xxh64_intdigest(t.encode(), 42)
        total += w
        for b in range(64):
            votes[b] += w * (h >> b & 1)
    return sum(1 << b for b in range(64) if 2 * votes[b] > total)


def check_edits(rows, found):
    rows = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or ""))
    want = Counter()
    for i, (d, t) in enumerate(rows):
        t, u = t or "", rows[(i + 1) % len(rows)][1] or ""
        q = len(t) // 4
        e = t[: len(t) - q] + u[:q]
        want[d, len(t), hashlib.sha256(e.encode()).hexdigest(), brute_vote(t), brute_vote(e), brute_vote(u)] += 1
    assert Counter((r.doc_id, r.n_chars, r.edited_sha256, r.fp % 2**64, r.edited_fp % 2**64, r.next_fp % 2**64) for r in found) == want


def test_edits_against_brute_force(spark, sf, monkeypatch):
    monkeypatch.setattr(simhash_search, "BUCKET_ROWS", 10)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    for some in (rows, EDGE, EDGE[:1], [(i % 7, f"t {i}") for i in range(50)]):
        df = spark.createDataFrame(some, SCHEMA).withColumn("bucket", F.lit(1))
        placed = simhash_search.fingerprint_edits(df)
        check_edits(some, placed.collect())
    assert simhash_search.fingerprint_edits(df.limit(0)).count() == 0


def test_two_levels_of_cuts(spark, monkeypatch):
    monkeypatch.setattr(simhash_search, "MOST_CUTS", 6)
    ids = [i * i % 977 for i in range(900)] + [None] * 5
    df = spark.createDataFrame([(i, f"t{n}") for n, i in enumerate(ids)], SCHEMA)
    placed = simhash_search.ordered_buckets(df, "doc_id", 10)
    spans = placed.where("not guest").groupBy("bucket").agg(F.min(F.coalesce("doc_id", F.lit(-1))).alias("lo"), F.max(F.coalesce("doc_id", F.lit(-1))).alias("hi")).orderBy("bucket").collect()
    assert len(spans) > 20 and all(a.hi < b.lo for a, b in zip(spans, spans[1:])) and [s.bucket for s in spans] == list(range(len(spans)))
    firsts = {r.bucket: r.lo for r in spans}
    guests = {r.bucket: r.i for r in placed.where("guest").groupBy("bucket").agg(F.min(F.coalesce("doc_id", F.lit(-1))).alias("i")).collect()}
    assert guests == {b: firsts[(b + 1) % len(spans)] for b in firsts}


def test_small_buckets_give_the_same(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    placed = simhash_search.ordered_buckets(docs, "doc_id", 7)
    n = docs.count()
    guests = placed.where("guest").count()
    assert placed.where("not guest").count() == n and guests == placed.select("bucket").distinct().count() > 10
    spans = placed.where("not guest").groupBy("bucket").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).orderBy("bucket").collect()
    assert all(a.hi < b.lo for a, b in zip(spans, spans[1:]))


def test_op9_query(spark, sf):
    q = registry.op9_document_fingerprints(spark, sf)
    rows = q.collect()
    fps = Counter(r.fingerprint for r in rows)
    all_fps = [int(r.fingerprint, 16) for r in rows]
    for r in rows[:60]:
        assert r.n_near == sum((x ^ int(r.fingerprint, 16)).bit_count() <= 3 for x in all_fps) - 1
        assert 0 <= r.near_edited <= 1 and fps[r.fingerprint] >= 1
    near = [r for r in rows if r.n_chars > 400]
    assert sum(r.near_edited for r in near) / len(near) > 0.7 > 0.6 > sum(r.near_next for r in near) / len(near)


def test_near_dedup_catches_copies_and_keeps_others(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()] + [(None, "kept"), (None, "kept")]
    df = spark.createDataFrame(rows, SCHEMA).withColumn("g", F.lit("extra"))
    kept = {r.doc_id for r in simhash_neardup.near_dedup(df).collect()}
    sets = {}
    for i, t in rows:
        if i is not None:
            w = simhash_neardup.words(t)
            sets[i] = {b" ".join(w[j : j + 5]) for j in range(max(1, len(w) - 4))}
    like = lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])
    ids = sorted(sets)
    pairs = [(a, b) for n, a in enumerate(ids) for b in ids[n + 1 :] if like(a, b)]
    linked = {b for _, b in pairs}
    assert not [i for i in ids if i not in linked and i not in kept]
    missed = [p for p in pairs if p[0] in kept and p[1] in kept]
    assert len(missed) <= 0.02 * len(pairs), (missed, len(pairs))


def test_settle_loses_no_link_of_a_crowded_bucket(spark):
    import random

    rnd = random.Random(5)
    rows = [(0, v, -1, i, i, 1, [0] * 8) for i in range(160) for v in ({i % 2, 2} if i < 150 else {3})]
    ring = {tuple(sorted((i, rnd.randrange(150)))) for i in range(150) for _ in range(rnd.randrange(2))}
    known = spark.createDataFrame([p for p in ring if p[0] != p[1]], "a bigint, b bigint")
    df = spark.createDataFrame(rows, "band int, v bigint, w bigint, rep bigint, side bigint, m int, o array<bigint>")
    found = simhash_neardup.settle(df, lambda pairs: pairs.join(known, ["a", "b"]), 0.8)
    up = list(range(160))
    for a, b in sorted(ring):
        x, y = sorted((up[a], up[b]))
        up = [x if u == y else u for u in up]
    linked = {r.node: r.component for r in found.labels.collect()}
    assert [linked.get(i, i) for i in range(160)] == up
    assert simhash_neardup.settle(df.limit(0), lambda pairs: pairs, 0.8).labels is None


def test_settle_loses_no_link_between_values(spark):
    import random

    rnd = random.Random(11)
    # 60 values in a row, each met by its two neighbours; value 7 is crowded and beside it are texts of no component
    at = {i: 7 if i < 120 else rnd.randrange(60) for i in range(400)}
    ways = [(0, v, w) for v in range(60) for w in (v - 1, v + 1) if 0 <= w < 60]
    links = {tuple(sorted((rnd.randrange(120), rnd.randrange(120)))) for _ in range(250)}
    links |= {tuple(sorted((rnd.randrange(400), rnd.randrange(400)))) for _ in range(3000)}
    links = {p for p in links if p[0] != p[1]}
    up = list(range(400))

    def link(pairs):
        for a, b in sorted(pairs):
            x, y = sorted((up[a], up[b]))
            up[:] = [x if u == y else u for u in up]

    inner = {p for p in links if at[p[0]] == at[p[1]] == 7}
    link(inner)
    start = simhash_neardup.Known(simhash_neardup.components(spark.createDataFrame(sorted(inner), "a bigint, b bigint")))
    link({p for p in links if abs(at[p[0]] - at[p[1]]) == 1})
    every = spark.createDataFrame(sorted(links), "a bigint, b bigint")
    members = spark.createDataFrame([(0, v, i, 1, [0] * 8) for i, v in at.items()], "band int, v bigint, rep bigint, m int, o array<bigint>")
    meet = spark.createDataFrame(ways, "band int, v bigint, w bigint")
    found = simhash_neardup.settle(members, lambda pairs: pairs.join(every, ["a", "b"]), 0.8, start, 1, meet)
    linked = {r.node: r.component for r in found.labels.collect()}
    assert [linked.get(i, i) for i in range(400)] == up
    tried = {(r.a, r.b) for t in found.tried for r in t.collect()}
    assert all(abs(at[a] - at[b]) == 1 for a, b in tried)


def test_members_beside_many_values_are_not_repeated(spark, monkeypatch):
    # 200 near copies at value 0 of band 4; 25 texts at the values one bit from it, of which only the first is a near copy
    words = [f"word{j}" for j in range(150)]
    rows = [(i, " ".join([*words[:j], f"new{i}", *words[j + 1 :]])) for i, j in ((i, i % 10) for i in range(201))]
    rows += [(i, " ".join(f"w{i}x{j}" for j in range(150))) for i in range(201, 225)]
    same, kept_tables = simhash_neardup.wide_fingerprints, []

    def placed(*a):
        first = F.when(F.col("doc_id") < 200, 5).otherwise(F.xxhash64("doc_id", F.lit(0)))
        beside = F.when(F.col("doc_id") < 200, 0).otherwise(F.expr("shiftleft(1L, int(doc_id - 200))"))
        apart = [F.xxhash64("doc_id", F.lit(k)) for k in range(1, 6)]
        third = F.shiftleft(apart[1], 32).bitwiseOR(beside)
        return same(*a).withColumn("f", F.array(first, apart[0], third, *apart[2:]))

    def counted(df, label):
        out = common.materialize(df, label)
        kept_tables.append((label, out.count()))
        return out

    monkeypatch.setattr(simhash_neardup, "wide_fingerprints", placed)
    monkeypatch.setattr(simhash_neardup, "materialize", counted)
    kept = {r.doc_id for r in simhash_neardup.near_dedup(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert kept == {0, *range(201, 225)}
    assert max(n for label, n in kept_tables if label in ("buckets", "members", "seen", "leaders")) <= 2 * len(rows)


def test_links_between_members_that_do_not_lead(spark):
    # 400 texts at one fingerprint; only the last two are alike
    text = lambda i: " ".join(f"w{i}x{j}" for j in range(100))
    rows = [(i, text(i)) for i in range(399)] + [(399, text(398) + " more")]
    df = spark.createDataFrame(rows, SCHEMA)
    same = simhash_neardup.wide_fingerprints
    simhash_neardup.wide_fingerprints = lambda *a: same(*a).withColumn("f", F.array(*[F.lit(5).cast("long")] * 4))
    try:
        kept = {r.doc_id for r in simhash_neardup.near_dedup(df).collect()}
    finally:
        simhash_neardup.wide_fingerprints = same
    assert kept == set(range(399))


def test_sketch_bound_keeps_all_like_sets(spark):
    import random

    rnd = random.Random(7)
    rows = []
    for i in range(60):
        w = [str(rnd.random()) for _ in range(rnd.randrange(20, 600))]
        rows += [(2 * i, " ".join(w)), (2 * i + 1, " ".join(w[: int(len(w) * rnd.uniform(0.6, 1))] + ["end"]))]
    sketches = {r.doc_id: r for r in simhash_neardup.wide_fingerprints(spark.createDataFrame(rows, SCHEMA), "doc_id", "text", 5).collect()}
    texts, like, passed = dict(rows), 0, 0
    for i in range(60):
        sets = [set(simhash_neardup.shingle_hashes(simhash_neardup.words(texts[2 * i + k]), 5)) for k in (0, 1)]
        x, y = sketches[2 * i], sketches[2 * i + 1]
        assert (x.m, y.m) == tuple(map(len, sets))
        apart = sum((a % 2**64 ^ b % 2**64).bit_count() for a, b in zip(x.o, y.o))
        assert apart <= len(sets[0] ^ sets[1])
        like += len(sets[0] & sets[1]) >= 0.8 * len(sets[0] | sets[1])
    df = spark.createDataFrame(list(sketches.values()))
    met = df.join(df.select(F.struct("doc_id", "m", "o").alias("l")), F.expr("doc_id + 1 = l.doc_id and doc_id % 2 = 0 and " + simhash_neardup.may_be_like(0.8)))
    assert 10 < like <= met.count() < 60


def test_near_copies_have_twelve_bands(spark):
    text = " ".join(f"word{i}" for i in range(80))
    row = simhash_neardup.wide_fingerprints(spark.createDataFrame([(1, text)], SCHEMA), "doc_id", "text", 5).first()
    halves = {(i, v >> s & simhash_neardup.HALF) for i, v in enumerate(row.f) for s in (0, 32)}
    assert len(row.f) == len(set(row.f)) == 6 and len({v for _, v in halves}) == 12


def test_near_dedup_defined_cases(spark):
    rows = [(1, None), (2, ""), (3, "  \n"), (4, "one"), (5, "ONE"), (5, "one"), (6, "word " * 200_000), (7, "word " * 200_000), (None, "one"), (None, None), (8, "a b c d e f")]
    df = spark.createDataFrame([(*r, 1, 2, 3) for r in rows], "doc_id bigint, text string, key int, rep int, f int")
    got = simhash_neardup.near_dedup(df)
    assert got.columns == df.columns
    assert Counter(r.doc_id for r in got.collect()) == {1: 1, 4: 1, 6: 1, 8: 1, None: 2}
    assert simhash_neardup.near_dedup(df.limit(0)).count() == 0


@pytest.mark.parametrize("most", [64 << 20, 0])
def test_hubs_and_chains_have_one_component(spark, monkeypatch, most):
    monkeypatch.setattr(common, "BROADCAST_BYTES", most)
    edges = [(0, i) for i in range(1, 4000)] + [(10_000 + i, 10_001 + i) for i in range(70)] + [(5, 5), (None, 3), (20_000, 20_001)]
    got = {r.node: r.component for r in simhash_neardup.components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert got == {i: 0 for i in range(4000)} | {10_000 + i: 10_000 for i in range(71)} | {20_000: 20_000, 20_001: 20_000}
