import itertools
import math
import random
import zlib

from tilerank.llm import registry
from tilerank.llm import toxicity as T

MODEL = T.Model({"idiot": (T.INSULT, 1.0), "scum": (T.INSULT, 1.0)}, {"lowei": (T.INSULT, 0.9)})


def weight(text):
    return sum(x for _, _, x in T.Scorer(MODEL).clauses(text))


def test_composition_equals_running_one_after_the_other():
    parts = [T.negation(), T.reported(), T.insult(), T.threat(), T.target()]
    whole = T.grammar()
    for word in itertools.product(range(7), repeat=5):
        states, total, state, got = [0] * 5, 0.0, 0, 0.0
        for symbol in word:
            x = 1.0 if symbol in (T.INSULT, T.THREAT) else 0.0
            s = symbol
            for i, m in enumerate(parts):
                states[i], s, f, w = m.step(states[i], s)
                x = x * f + w
            total += x
            state, _, f, w = whole.arcs[state, symbol]
            got += (1.0 if symbol in (T.INSULT, T.THREAT) else 0.0) * f + w
        assert abs(total - got) < 1e-9


def test_clauses_weigh_context():
    assert weight("you idiot") > weight("an idiot") > weight("not an idiot") > 0
    assert weight("he said: fine. an idiot") == weight("an idiot") > weight("someone called it idiot")
    assert weight('"idiot"') < weight("idiot") < weight("idiot scum") < 2 * weight("idiot")
    assert weight("i will kill you") < weight("you i will kill")
    assert weight("idiotic loweit alowei") == 0.9 and weight("midiot idiots") == 0 and weight(None) == weight("") == 0
    spans = T.Scorer(MODEL).clauses("Fine. The IDIOT, here; and scum\nok")
    assert [(a, b) for a, b, _ in spans] == [(5, 21), (22, 31)]


def test_long_texts_and_every_clause():
    text = "plain words here. " * 100_000 + "an idiot."
    assert weight(text) == weight("an idiot") and weight("an idiot. " * 1000) == 1000 * weight("an idiot")


def test_learns_from_labels_outside_the_fold(spark):
    rows, labels = [], []
    for i in range(600):
        toxic = i % 5 == 0
        rows.append((i, f"alpha beta {'zorgu' + 'abcdefgh'[i % 8] if toxic else 'gamma'} w{i}" if i != 3 else None, "x"))
        labels.append((i, int(toxic)))
    labels += [(7, None), (None, 1), (5, 1)]
    docs = spark.createDataFrame([*rows, (None, "zorguq", "x"), (1, "alpha", "x")], "doc_id bigint, text string, toxic string")
    model = T.train(docs, spark.createDataFrame(labels, "doc_id bigint, toxic int"))
    assert any(s.startswith("zor") for s in model.stems)
    got = {(r.doc_id, r.text): r.score for r in T.with_scores(docs, model).collect()}
    assert all((got[i, t] >= 0.5) == (i % 5 == 0) for i, t, _ in rows)
    assert got[None, "zorguq"] >= 0.5 > got[3, None] > 0
    assert T.reject(docs, model).count() == docs.count() - 121 and T.reject(docs, model).columns == docs.columns
    empty = T.train(docs.limit(0), spark.createDataFrame([], "doc_id bigint, toxic int"))
    assert T.with_scores(docs, empty).count() == docs.count() and T.with_scores(docs.limit(0), empty).count() == 0


def test_query_shape_and_held_out_fold(spark, sf):
    rows = registry.op4_toxicity(spark, sf).collect()
    assert len(rows) == spark.read.parquet(f"{sf}/documents.parquet").count()
    for r in rows:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and r.predicted == (r.score >= 0.5) and 0 <= r.score <= 1


def test_held_out_documents_are_told_apart(spark):
    sf = "/root/testdata/sf0.1"  # smaller tables hold out six toxic documents only
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    rows = [(r.score, labels[r.doc_id]) for r in registry.op4_toxicity(spark, sf).collect() if r.held_out and r.doc_id in labels]
    toxic, clean = [s for s, t in rows if t], [s for s, t in rows if not t]
    order = sum((a > b) + 0.5 * (a == b) for a in toxic for b in clean) / (len(toxic) * len(clean))
    assert len(toxic) > 5 and order > 0.95, order
    assert sum(s >= 0.5 for s in clean) <= 0.02 * len(clean)


def brute_score(model, text):
    """The score word by word: each clause found by its own search, each token looked up in the lexicon, the five machines one after the other."""
    closed, out = T.closed_classes(), []
    clauses, start = [], 0
    low = text.lower()
    for i, c in enumerate(low + "\n"):
        if c in T.CLAUSE_MARKS:
            clauses.append(low[start:i])
            start = i + 1
    for clause in clauses:
        kinds = []
        for token in T.TOKEN.findall(clause):
            found = (T.QUOTE, 0.0) if token in T.QUOTES else closed.get(token)
            if token in model.words:
                found = model.words[token]
            if found is None:
                stems = [model.stems[token[:n]] for n in range(len(token) - 1, 0, -1) if token[:n] in model.stems]
                found = stems[0] if stems else (T.OTHER, 0.0)
            kinds.append(found)
        if not any(k in (T.INSULT, T.THREAT) for k, _ in kinds):
            continue
        parts, total = [T.negation(), T.reported(), T.insult(), T.threat(), T.target()], 0.0
        states = [0] * 5
        for symbol, weight in kinds:
            x = weight if symbol in (T.INSULT, T.THREAT) else 0.0
            for i, m in enumerate(parts):
                states[i], symbol, f, w = m.step(states[i], symbol)
                x = x * f + w
            total += x
        if total > 0:
            out.append(total)
    a, b, c = model.coefficients
    return 1 / (1 + math.exp(-(a + b * max(out, default=0.0) + c * math.log1p(sum(out)))))


def test_scores_equal_brute_force():
    rnd = random.Random(6)
    words = "you idiot scum not never said the a house kill lowein loweis he goes \" . ! ; fine hurt them".split()
    model = T.Model({"idiot": (T.INSULT, 1.0), "scum": (T.INSULT, 0.8)}, {"lowei": (T.INSULT, 0.9)})
    scorer = T.Scorer(model)
    for _ in range(300):
        text = " ".join(rnd.choice(words) for _ in range(rnd.randrange(25)))
        assert abs(scorer.score(text) - brute_score(model, text)) < 1e-9, text
