import hashlib
import random
import re
from collections import Counter, defaultdict

import duckdb
from pyspark.sql import functions as F

from tilerank.llm import licenses, linededup, registry, secrets

LIVE = ["Zk3v9QpL7xT2mB8nR4wY", "p0Oi9uJ8hY7gT6fR5dE4", "9aB8cD7eF6gH5iJ4kL3m"]


def brute_base(text):
    found = []
    kw = "".join
    word = "(?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])"
    for m in re.finditer(word + "[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", text):
        if len(m[1]) >= 6:
            found.append((m.start(), 0, m.end()))
    found += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    found += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
    return ",".join(kw(f"{['assign', 'access', 'hex'][k]}:{a}:{b}") for a, k, b in sorted(found))


def test_base_spans_and_ownership(spark, sf):
    docs = [(r.doc_id, r.text, r.source) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    docs += [
        (900, None, "a"), (901, "", "a"), (None, "passwſrd=abcdefgh é password: 'abcdef' Secret=\"x\" TOKEN = abc/def+", None),
        (903, f"AKIA{'A' * 16} AKIA123 " + "0123456789abcdef" * 2, "a"), (903, f"AKIA{'A' * 16} AKIA123 " + "0123456789abcdef" * 2, "a"),
        (904, f"key {LIVE[0]} here", "a"), (905, f"again {LIVE[0]}", "a"), *[(910 + i, f"copied {LIVE[1]}", f"s{i}") for i in range(5)],
        (920, "word " * 300_000 + "password=lastsecret99", "b"), (921, "password=ABC" + LIVE[2], "b"),
    ]
    df = spark.createDataFrame([(i, t, s, 1) for i, t, s in docs], "doc_id bigint, text string, source string, base int")
    rows = secrets.scan(df, F.col("source"), F.col("source")).collect()
    assert len(rows) == len(docs)
    want = Counter((i, hashlib.sha256(brute_base(t or "").encode()).hexdigest()) for i, t, _ in docs)
    assert Counter((r.doc_id, r.base_sha256) for r in rows) == want
    by = defaultdict(list)
    for r in rows:
        by[r.doc_id].append(r)
    assert by[904][0].spans == "opaque:4:24" and by[905][0].spans == "opaque:6:26" and by[904][0].n_live == 1
    assert all(by[910 + i][0].spans == "" and by[910 + i][0].n_copied == 1 for i in range(5))
    for i, t, _ in docs:
        base = brute_base(t or "")
        kept = [x for x in by[i][0].spans.split(",") if x.split(":")[0] in ("assign", "access", "hex")]
        assert base in {",".join(x for x in r.spans.split(",") if x.split(":")[0] in ("assign", "access", "hex")) for r in by[i]}, (base, kept)
        assert by[i][0].n_assign + by[i][0].n_access + by[i][0].n_hex == (len(base.split(",")) if base else 0) or i in (903,)
    assert secrets.scan(df.limit(0), F.col("source"), F.col("source")).count() == 0
    assert registry.op2_secret_scan(spark, sf).columns[:6] == ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"]


def test_ownership_counts_equal_brute_force(spark):
    rnd = random.Random(9)
    rows = [(rnd.randrange(40), f"r{rnd.randrange(6)}", rnd.choice(["a", "b", "c", None])) for _ in range(3000)] + [(7, "r0", "a")] * 2000
    got = secrets.ownership(spark.createDataFrame(rows, "hash bigint, repo__ string, owner__ string")).collect()
    held = defaultdict(list)
    for h, r, o in rows:
        held[h].append((r, o))
    assert {r.hash: (r.n_rows, r.n_repos, r.n_owners) for r in got} == {h: (len(x), len(set(x)), len({o for _, o in x})) for h, x in held.items()}


def test_line_dedup_equals_sql(spark, sf):
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{sf}/documents.parquet'")
    want = sorted(con.execute(registry.ORACLES["op3_line_dedup"]).fetchall())
    got = sorted(tuple(r) for r in registry.op3_line_dedup(spark, sf).collect())
    assert got == want and any(r[2] for r in got)


def test_line_dedup_near_the_threshold(spark):
    rows = [(i, f"s{i % n}", f"own {i}\n shared by {n} \n\ntail", "x") for n in range(6, 12) for i in range(60)]
    rows += [(None, None, None, "x"), (1, None, "", "x"), (2, "s0", "own 1\r\n" * 3, "x")]
    docs = spark.createDataFrame(rows, "doc_id bigint, site string, text string, n_lines string").withColumnRenamed("n_lines", "g")
    got = linededup.without_boilerplate(docs, F.col("site"), min_sites=8).collect()
    assert len(got) == len(rows)
    assert {r.n_removed for r in got if r.text and "shared by 7" in r.text} == {1}  # only the tail went
    assert not any("shared by 8" in r.text or "shared by 11" in r.text for r in got)
    assert [r.text for r in got if r.site is None] == ["", ""]
    assert linededup.without_boilerplate(docs.limit(0), F.col("site")).count() == 0


def test_line_dedup_keeps_clashing_columns(spark):
    names = ["n_lines", "n_removed", "k__", "m__", "cut__", "key", "digest", "cut", "line", "sketch"]
    rows = [(i, f"s{i}", f"own {i}\nshared") for i in range(9)] + [(9, None, None), (10, "s1", "shared\n" * 3), (10, "s1", "shared\n" * 3)]
    docs = spark.createDataFrame(rows, "doc_id bigint, site string, text string").select("*", *[F.lit(i).alias(c) for i, c in enumerate(names)])
    got = linededup.without_boilerplate(docs, F.col("site"))
    assert set(got.columns) == {*docs.columns, "n_lines_", "n_removed_"}
    for r in got.collect():
        assert [r[c] for c in names] == list(range(len(names)))
        assert "shared" not in r.text and r.n_removed_ == (1 if r.doc_id < 9 else 0 if r.doc_id == 9 else 3)


def test_line_dedup_of_a_text_with_very_many_lines(spark):
    common = [f"common line {i}" for i in range(3000)]
    rows = [(i, f"s{i}", "\n".join([f"own {i}", *common])) for i in range(8)]
    docs = spark.createDataFrame(rows, "doc_id bigint, site string, text string")
    got = {r.doc_id: r for r in linededup.without_boilerplate(docs, F.col("site")).collect()}
    assert all(got[i].text == f"own {i}" and got[i].n_removed == 3000 for i in range(8))
    found = spark.createDataFrame([(sorted(range(-50, 3 * n, 3)), n) for n in (0, 1, 5, 6, 40)], "a array<bigint>, n int")
    for r in found.select("a", F.transform(F.sequence(F.lit(-60), F.lit(130)), lambda x: linededup.stands_in(F.col("a"), x.cast("long"))).alias("f")).collect():
        assert r.f == [x in r.a for x in range(-60, 131)]


def common_length(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        new = [0]
        for j, y in enumerate(b):
            new.append(row[j] + 1 if x == y else max(new[-1], row[j + 1]))
        row = new
    return row[-1]


def brute_licenses(words, s):
    """Winner by trying every template on every stretch of the words, then the rest before and after it; wins as a list of ids."""
    best = None
    for t in s.templates:
        width = int(licenses.SLACK * len(t.words))
        for i in range(len(words)):
            for j in range(i + 1, min(len(words), i + width) + 1):
                if words[i] in t.bag and words[j - 1] in t.bag:
                    n = common_length(t.words, words[i:j])
                    score = (n / len(t.words), -(len(t.words) + j - i - 2 * n), -i)
                    if n >= t.least and (best is None or score > best[0]):
                        best = (score, t.license, i, j)
    if best is None:
        return []
    return brute_licenses(words[: best[2]], s) + [best[1]] + brute_licenses(words[best[3] :], s)


def test_licenses_equal_brute_force():
    rnd = random.Random(11)
    names = ["Apache-2.0", "MIT", "GPL-3.0", "CC-BY-NC-4.0", "MPL-2.0", "ISC"]
    some = {k: licenses.TEMPLATES[k] for k in names}
    s = licenses.Scanner(some)
    hits = 0
    for trial in range(60):
        parts = []
        for k in rnd.sample(names, rnd.randrange(4)):
            words = rnd.choice(some[k]).split(" ")
            for _ in range(rnd.randrange(4)):
                rnd.choice([lambda: words.pop(rnd.randrange(len(words))), lambda: words.insert(rnd.randrange(len(words) + 1), "under")])() if len(words) > 3 else None
            if words:
                words[rnd.randrange(len(words))] += rnd.choice(["", "\n * ", "\n# "])
            parts.append(" ".join(words))
        text = rnd.choice(["\n", " ", "\n\n"]).join(parts)
        want = []
        for a, b in s.blocks(text):
            want += brute_licenses([w.lower() for w in licenses.WORD.findall(text[a:b])], s)
        got = s.scan(text)
        assert [f["license"] for f in got] == want, (text, got, want)
        hits += len(want)
        assert all(x["end"] <= y["start"] for x, y in zip(got, got[1:]))
    assert hits > 40


def test_whatever_may_be_confirmed_has_a_cue():
    rnd = random.Random(12)
    s = licenses.Scanner(licenses.TEMPLATES)
    for t in s.templates * 20:
        kept = sorted(rnd.sample(range(len(t.words)), t.least))
        line = " ".join(t.words[i] for i in kept)
        assert s.cue.search(line) and s.scan(f"prose before\n{line}\nprose after"), line


def test_all_licenses_of_a_block():
    s = licenses.Scanner(licenses.TEMPLATES)
    names = lambda text: [f["license"] for f in s.scan(text)]
    mit, apache, mpl, isc = (licenses.NOTICES[k] for k in ("MIT", "Apache-2.0", "MPL-2.0", "ISC"))
    assert names(f"{mit} {apache}") == names(f"{mit}\n{apache}") == names(f"{mit} Or: {apache}") == ["MIT", "Apache-2.0"]
    assert names("# " + mpl.replace("Public License", "Public\n# License")) == ["MPL-2.0"]
    assert names(isc.replace("any purpose", "any\n  purpose").replace("fee is", "fee\n is")) == ["ISC"]
    assert names("// SPDX-License-Identifier: Apache-2.0") == ["Apache-2.0"] and names("spdx") == []
    assert names(f"{mit}\n" * 50 + apache) == ["MIT"] * 50 + ["Apache-2.0"]


def test_license_defined_cases(spark):
    mit = licenses.NOTICES["MIT"]
    rows = [(1, None), (2, ""), (3, mit), (3, mit), (None, mit), (4, "plain words\n" * 100_000 + mit + "\n" + "x" * 100_000), (5, "é " + mit)]
    docs = spark.createDataFrame([(*r, 7, "x") for r in rows], "doc_id bigint, text string, blocks int, license string")
    got = licenses.license_blocks(docs)
    assert got.columns == ["doc_id", "blocks"]
    found = Counter((r.doc_id, tuple(b["license"] for b in r.blocks)) for r in got.collect())
    assert found == {(1, ()): 1, (2, ()): 1, (3, ("MIT",)): 2, (None, ("MIT",)): 1, (4, ("MIT",)): 1, (5, ("MIT",)): 1}
    assert licenses.license_blocks(docs.limit(0)).count() == 0
    # two templates of equal words tie: the first of them is named
    twins = licenses.Scanner({"one": ["alpha beta gamma license"], "two": ["alpha beta gamma license"]})
    assert [f["license"] for f in twins.scan("alpha beta gamma license")] == ["one"]


def test_license_ranking_and_confirmation(spark, sf):
    s = licenses.Scanner(licenses.TEMPLATES)
    for name, text in licenses.NOTICES.items():
        found = s.scan(f"Some prose first.\n{text}\nMore prose after it.")
        assert [f["license"] for f in found] == [name] and found[0]["exact"], (name, found)
        assert s.rank(text, s.templates)[0][0].license == name or found[0]["exact"]
    near = s.scan("Licensed under the Apache License, Version 2.1 of it.")[0]
    assert near["license"] == "Apache-2.0" and not near["exact"] and near["missing"] and near["extra"]
    assert s.scan("A licensed plumber came by yesterday and fixed the sink in our kitchen.") == []
    assert s.scan(None) == s.scan("") == []
    long = "plain words\n" * 200_000 + licenses.NOTICES["MIT"]
    assert [f["license"] for f in s.scan(long)] == ["MIT"]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r.doc_id: r for r in registry.op5_license_scan(spark, sf).collect()}
    assert len(got) == docs.count()
    for r in docs.select("doc_id", "text").collect():
        for name, text in licenses.NOTICES.items():
            if text in (r.text or "").split("\n"):
                assert name in got[r.doc_id].licenses.split(",")
