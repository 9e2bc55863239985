import random

import numpy as np
from pyspark.sql import functions as F

from tilerank.llm import decontaminate as D
from tilerank.llm import registry


def edit_distance_inside(w, t):
    """Least edits between w and any part of t."""
    return int(distances_inside(np.array([w]), np.array(t))[0])


def distances_inside(w, t):
    """The same for each row of w, by the whole table of w against t."""
    w, t = np.atleast_2d(w), np.asarray(t)
    steps = np.arange(len(t) + 1)
    row = np.zeros((len(w), len(t) + 1), int)
    for i in range(w.shape[1]):
        new = np.empty_like(row)
        new[:, 0] = i + 1
        new[:, 1:] = np.minimum(row[:, 1:] + 1, row[:, :-1] + (w[:, i : i + 1] != t))
        row = np.minimum.accumulate(new - steps, 1) + steps
    return row.min(1)


def brute(text, items):
    t = D.normal(text, TABLE)
    found = set()
    for i, s in items:
        a = D.normal(s, TABLE)
        sizes = {hi - lo for lo, hi in D.windows(len(a))} if len(a) >= D.MIN_CHARS else ()
        if any((distances_inside(np.lib.stride_tricks.sliding_window_view(a, n), t) <= D.budget(n)).any() for n in sizes):
            found.add(i)
    return sorted(found)


TABLE = D.code_table()


def noisy(rnd, text, edits):
    s = list(text)
    for _ in range(edits):
        p = rnd.randrange(len(s))
        rnd.choice([lambda: s.pop(p), lambda: s.insert(p, rnd.choice("abcde ")), lambda: s.__setitem__(p, rnd.choice("xyzé"))])()
    return "".join(s)


def test_finder_equals_whole_alignment():
    rnd = random.Random(5)
    word = lambda: "".join(rnd.choice(["th", "er", "on", "an", "é", "ti"]) for _ in range(rnd.randrange(1, 5)))
    prose = lambda n: " ".join(word() for _ in range(n))
    items = [(i, prose(n)) for i, n in enumerate([8, 14, 25, 40, 60])] + [(90, "too short")]
    finder = D.Finder(D.ItemIndex(items))
    hits = 0
    for trial in range(60):
        i, s = items[trial % 5]
        part = s if trial % 3 else s[: rnd.randrange(len(s) // 2, len(s))]
        text = prose(10) + " " + noisy(rnd, part, rnd.randrange(14)) + " " + prose(10)
        want = brute(text, items)
        assert sorted(finder.of(text)) == want, (trial, text)
        hits += bool(want)
    assert 10 < hits < 60


def test_grams_are_positional():
    a = np.array([1, 2, 3, 1, 2, 3, 1, 2, 3, 4, 5, 9, 1, 2, 3, 1, 2, 3, 1, 2, 3, 4, 5, 8], np.uint32)
    for n in (1, 3, 8, 11, 15):
        g = D.grams(a, n)
        runs = [tuple(a[i : i + n]) for i in range(len(a) - n + 1)]
        assert len(g) == len(runs) and len(set(g.tolist())) == len(set(runs))
        assert all((g[i] == g[j]) == (runs[i] == runs[j]) for i in range(len(runs)) for j in range(len(runs)))


def test_edges_and_blocks(spark, monkeypatch):
    item = "The quick brown fox jumps over the lazy dog and runs away from the big bear."
    docs = spark.createDataFrame(
        [(1, None, 1), (2, "", 2), (3, f"x {item.upper()} y", 3), (3, f"x {item.upper()} y", 3), (None, item, 4), (5, "plain " * 400_000 + item, 5), (6, "fox", 6)],
        "doc_id bigint, text string, item_id int",
    )
    bench = spark.createDataFrame([(7, item), (7, item), (None, item), (8, None), (9, ""), (10, "fox"), (11, "nothing of that sort is in any of these texts")], "item_id bigint, text string")
    want = {(1, 0), (2, 0), (3, 1), (None, 1), (5, 1), (6, 1)}
    got = D.leaks(docs, bench).collect()
    assert {(r.doc_id, len(r.leaked_items)) for r in got} == want and len(got) == 7 and {tuple(r.leaked_items) for r in got} == {(), (7,), (10,)}
    assert sorted(r.doc_id for r in D.clean(docs, bench).collect()) == [1, 2]
    assert D.clean(docs, bench).columns == docs.columns
    assert D.clean(docs, bench.limit(0)).count() == 7 and D.clean(docs.limit(0), bench).count() == 0
    monkeypatch.setattr(D, "ITEM_BLOCK", 60)
    assert {(r.doc_id, len(r.leaked_items)) for r in D.leaks(docs, bench).collect()} == want


def test_query_finds_all_whole_passages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    bench = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    got = {r.doc_id: set(r.item_ids) for r in registry.op8_benchmark_decontamination(spark, sf).collect()}
    assert len(got) == docs.count()
    for r in docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).collect():
        assert {i for i, t in bench if t in r.text} <= got[r.doc_id]


def test_any_part_of_an_item_counts():
    rnd = random.Random(11)
    prose = lambda n: " ".join("".join(rnd.choice("abcdefghijklmno") for _ in range(rnd.randrange(2, 9))) for _ in range(n))
    for size in (125, 180, 181, 300, 700):
        item = D.normal(prose(200), TABLE)[:size]
        item[[0, -1]] = ord("q")
        s = "".join(map(chr, item))
        finder = D.Finder(D.ItemIndex([(1, s)]))
        whole = [x for x in range(size - 119) if s[x] != " " != s[x + 119]]
        for lo in {whole[0], whole[-1], whole[len(whole) // 2], whole[len(whole) // 3], min(whole, key=lambda x: abs(x - 50))}:
            cut = s[lo : lo + 120]
            assert finder.of(f"{prose(30)} {cut} {prose(30)}") == {1}, (size, lo)
            changed = list(cut)
            for j in rnd.sample(range(120), 6):
                changed[j] = "z" if j % 2 else ""
            text = f"{prose(30)} {''.join(changed)} {prose(30)}"
            assert (finder.of(text) == {1}) == bool(brute_all(text, s)), (size, lo)
        assert finder.of(f"{prose(30)} {s[:90]} {prose(30)}") == set()


def brute_all(text, s):
    """Whether a part of WINDOW characters at any offset, or a short item as a whole, is in the text within its budget."""
    t, a = D.normal(text, TABLE), D.normal(s, TABLE)
    for n in {min(len(a), D.WINDOW), len(a) if len(a) <= 180 else D.WINDOW}:
        los = np.arange(len(a) - n + 1)
        row = np.zeros((len(los), len(t) + 1), np.int64)
        steps = np.arange(len(t) + 1)
        for i in range(n):
            diagonal = row[:, :-1] + (t[None, :] != a[los + i][:, None])
            new = np.concatenate([row[:, :1] + 1, np.minimum(diagonal, row[:, 1:] + 1)], 1)
            row = np.minimum.accumulate(new - steps, 1) + steps
        if (row.min(1) <= D.budget(n)).any():
            return True
    return False


def test_finder_equals_alignment_at_all_offsets():
    rnd = random.Random(6)
    word = lambda: "".join(rnd.choice(["th", "er", "on", "an", "é", "ti"]) for _ in range(rnd.randrange(1, 5)))
    prose = lambda n: " ".join(word() for _ in range(n))
    items = [(i, prose(n)) for i, n in enumerate([8, 14, 25, 40, 60])]
    finder = D.Finder(D.ItemIndex(items))
    hits = 0
    for trial in range(60):
        s = items[trial % 5][1]
        lo = rnd.randrange(len(s) // 2)
        part = s[lo : lo + rnd.randrange(100, 200)]
        text = prose(10) + " " + noisy(rnd, part, rnd.randrange(12)) + " " + prose(10)
        want = {i for i, t in items if brute_all(text, t)}
        assert finder.of(text) == want, (trial, text)
        hits += bool(want)
    assert 10 < hits < 60


def test_short_items_count_where_they_stand_alone(spark):
    items = spark.createDataFrame([(1, "What is two?"), (2, "--"), (3, None), (None, "Alone here"), (4, "Alone, here")], "item_id bigint, text string")
    rows = [(1, "what is TWO"), (2, "so what is two then"), (3, "first\n * What is two?\nlast"), (4, "--"), (5, None), (6, ""), (7, "x\nalone here")]
    docs = spark.createDataFrame([(*r, 1, 2) for r in rows], "doc_id bigint, text string, leaked_items int, leaked_items__0 int")
    got = D.leaks(docs, items)
    assert got.columns == [*docs.columns, "leaked_items_"]
    assert {r.doc_id: r.leaked_items_ for r in got.collect()} == {1: [1], 2: [], 3: [1], 4: [], 5: [], 6: [], 7: [4]}
    kept = D.clean(docs, items)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {2, 4, 5, 6} and kept.first().leaked_items__0 == 2


def test_many_and_long_items_travel_in_blocks(spark, monkeypatch):
    rnd = random.Random(8)
    prose = lambda n: " ".join("".join(rnd.choice("abcdefghij") for _ in range(rnd.randrange(2, 9))) for _ in range(n))
    items = [(i, prose(40)) for i in range(12)] + [(50, prose(900))]
    monkeypatch.setattr(D, "ITEM_BLOCK", 1500)
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    blocks = list(D.item_blocks(bench, "item_id", "text"))
    assert len(blocks) > 4 and all(sum(len(t) for _, t in b) <= 1500 for b in blocks)
    texts = [(i, prose(10) + " " + s[at : at + 130] + " " + prose(10)) for i, s in items for at in range(0, max(1, len(s) - 130), 200)]
    docs = spark.createDataFrame([(n, t) for n, (_, t) in enumerate(texts)], "doc_id bigint, text string")
    got = {r.doc_id: r.leaked_items for r in D.leaks(docs, bench).collect()}
    assert all(texts[n][0] in got[n] for n in got)


def test_repetitive_items_and_texts_are_bounded(monkeypatch):
    monkeypatch.setattr(D, "HITS", 1000)
    finder = D.Finder(D.ItemIndex([(1, "ab " * 400), (2, "0 " * 100 + "unlike anything else that is written here or there " * 4)]))
    assert finder.of("ab " * 5000) == {1} and finder.of("0 " * 3000) == set() or finder.of("0 " * 3000) == {2}
    assert finder.of("a" * 5000) == set()
