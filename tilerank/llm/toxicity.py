"""Toxicity by a weighted finite-state grammar over clauses.

Tokens are mapped to a small alphabet by a lexicon (insults and threats with weights, targets, negation, reporting
words, quotes, the rest). Five transducers over it - insult, threat, target, negation, reported
speech - are composed into one deterministic machine; a clause that holds an insult or a threat is run through it
and gets the machine's weight. Words outside such clauses never add to a score. A logistic model
over the largest and the summed clause weight turns them into a score from 0 to 1.

The lexicon is learned: words and word beginnings whose document counts in labelled rows tie them to the toxic
label beyond chance (likelihood ratio against the number of candidates), beside a short public seed list.
Only the text is read for a score; learning takes at most MAX_TRAIN labelled documents (chosen by hash) and
leaves out those whose CRC-32 of the id is a multiple of FOLDS.

Defined cases: null text is empty; an empty text, or one without a matched clause, gets the model's base score;
a document labelled twice is toxic if any row says so; null labels are ignored; a null doc_id is never held out;
without toxic training rows the seed list and the prior weights stand; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import product

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name, materialize, text_of

FOLDS, MAX_TRAIN = 5, 8000
STEMS = (3, 4, 5, 6, 7, 8)

# Fixed word lists of the seed lexicon and the closed classes.
SEED_INSULTS = "idiot stupid moron scum trash loser pathetic worthless disgusting clown imbecile bastard filth vermin dumb".split()
THREATS = "kill hurt destroy beat punch stab shoot strangle tuer frapper töten schlagen matar golpear".split()
TARGETS = "you your yours u he she they them tu toi vous du dich sie ihr tú usted ustedes vosotros ellos".split()
NEGATIONS = "not never no isn't aren't wasn't don't ne pas jamais nicht kein keine nie nunca jamás".split()
REPORTS = "said says say called calls quoted wrote claims claimed reported alleged dit disait écrit sagte sagt schrieb nannte dijo dice escribió llamó".split()
CLAUSE_MARKS = ".!?;:\n"
CLAUSE_END = re.compile(f"[{CLAUSE_MARKS}]")
TOKEN = re.compile(r"[^\W_]+(?:'[^\W_]+)*|[\"“”«»]")
OTHER, INSULT, THREAT, TARGET, NEGATION, REPORT, QUOTE = range(7)


@dataclass
class Transducer:
    """A complete deterministic machine: (state, symbol) -> (state, output symbol, factor on the token's weight, added weight)."""

    states: int
    arcs: dict[tuple[int, int], tuple[int, int, float, float]] = field(default_factory=dict)

    def step(self, state: int, symbol: int) -> tuple[int, int, float, float]:
        return self.arcs.get((state, symbol), (state, symbol, 1.0, 0.0))

    def compose(self, after: Transducer) -> Transducer:
        """The machine that feeds this one's output to ``after``; factors multiply, weights add."""
        made = Transducer(self.states * after.states)
        for (p, q), s in product(product(range(self.states), range(after.states)), range(7)):
            p2, mid, f1, w1 = self.step(p, s)
            q2, out, f2, w2 = after.step(q, mid)
            made.arcs[p * after.states + q, s] = (p2 * after.states + q2, out, f1 * f2, w1 * f2 + w2)
        return made


def negation(reach: int = 3, damp: float = 0.6) -> Transducer:
    """An insult or threat within ``reach`` tokens after a negation counts for less."""
    t = Transducer(reach + 1)
    for s in range(reach + 1):
        t.arcs[s, NEGATION] = (reach, NEGATION, 1.0, 0.0)
        for c in (OTHER, TARGET, REPORT, QUOTE):
            t.arcs[s, c] = (max(0, s - 1), c, 1.0, 0.0)
        for c in (INSULT, THREAT):
            t.arcs[s, c] = (max(0, s - 1), c, damp if s else 1.0, 0.0)
    return t


def reported(damp: float = 0.6) -> Transducer:
    """After a reporting word, or inside quotes, what is said counts for less."""
    t = Transducer(4)  # bit 0: reported, bit 1: inside quotes
    for s in range(4):
        t.arcs[s, REPORT] = (s | 1, REPORT, 1.0, 0.0)
        t.arcs[s, QUOTE] = (s ^ 2, QUOTE, 1.0, 0.0)
        for c in (INSULT, THREAT):
            t.arcs[s, c] = (s, c, damp if s else 1.0, 0.0)
    return t


def target(bonus: float = 0.5) -> Transducer:
    """A person spoken of in the clause adds to the insults and threats beside it, once."""
    t = Transducer(4)  # 0 nothing, 1 target seen, 2 insult or threat seen, 3 paid
    for c in (INSULT, THREAT):
        t.arcs[0, c] = (2, c, 1.0, 0.0)
        t.arcs[1, c] = (3, c, 1.0, bonus)
    t.arcs[0, TARGET] = (1, TARGET, 1.0, 0.0)
    t.arcs[2, TARGET] = (3, TARGET, 1.0, bonus)
    return t


def insult(repeat: float = 0.5) -> Transducer:
    """The first insult of a clause counts in full, further ones in part."""
    t = Transducer(2)
    t.arcs[0, INSULT] = (1, INSULT, 1.0, 0.0)
    t.arcs[1, INSULT] = (1, INSULT, repeat, 0.0)
    return t


def threat(alone: float = 0.2) -> Transducer:
    """A threat counts in full against somebody named before it, and little alone."""
    t = Transducer(2)
    t.arcs[0, TARGET] = (1, TARGET, 1.0, 0.0)
    t.arcs[0, THREAT] = (0, THREAT, alone, 0.0)
    return t


def grammar() -> Transducer:
    """Negation and reported speech damp, then insults, threats and targets are weighed."""
    return negation().compose(reported()).compose(insult()).compose(threat()).compose(target())


@dataclass
class Model:
    """``words``: token -> (class, weight); ``stems``: word beginning -> (class, weight); logistic coefficients."""

    words: dict[str, tuple[int, float]]
    stems: dict[str, tuple[int, float]]
    coefficients: tuple[float, float, float] = (-3.0, 4.0, 0.3)


def closed_classes() -> dict[str, tuple[int, float]]:
    named = [(TARGETS, TARGET, 0.0), (NEGATIONS, NEGATION, 0.0), (REPORTS, REPORT, 0.0), (THREATS, THREAT, 1.0)]
    return {w: (c, x) for ws, c, x in named for w in ws}


class Scorer:
    def __init__(self, model: Model):
        self.words, self.stems = closed_classes() | model.words, model.stems
        self.lengths = sorted({len(s) for s in self.stems})
        self.arcs = grammar().arcs
        self.bias, self.by_max, self.by_sum = model.coefficients
        self.cores = ahocorasick.Automaton()
        for w in {w for w, (c, _) in self.words.items() if c in (INSULT, THREAT)} | set(self.stems):
            self.cores.add_word(w, (len(w), w not in self.stems))
        self.cores.make_automaton()

    def symbol(self, token: str) -> tuple[int, float]:
        """Class and weight: of the word, or of the weightiest matching stem, whichever weighs more."""
        best = self.words.get(token, (OTHER, 0.0))
        for n in self.lengths:
            if n < len(token) and (s := self.stems.get(token[:n])) and s[1] > best[1]:
                best = s
        return best

    def clause(self, tokens: list[str]) -> float:
        state, total = 0, 0.0
        for t in tokens:
            c, x = (QUOTE, 0.0) if t in QUOTES else self.symbol(t)
            state, _, factor, added = self.arcs[state, c]
            total += x * factor + added
        return total

    def clauses(self, text: str | None) -> list[tuple[int, int, float]]:
        """Start, end and weight of each clause with an insult or a threat, over the whole lower-cased text."""
        low = (text or "").lower()
        found, done = [], -1
        for end, (n, whole) in self.cores.iter(low):
            start = end - n + 1
            if start < done or start and low[start - 1].isalnum() or whole and low[end + 1 : end + 2].isalnum():
                continue
            a = start
            while a > done and a and low[a - 1] not in CLAUSE_MARKS:
                a -= 1
            m = CLAUSE_END.search(low, end + 1)
            done = m.start() if m else len(low)
            weight = self.clause(TOKEN.findall(low[a:done]))
            if weight > 0:
                found.append((a, done, weight))
        return found

    def features(self, text: str | None) -> tuple[float, float]:
        w = [x for _, _, x in self.clauses(text)]
        return max(w, default=0.0), math.log1p(sum(w))

    def score(self, text: str | None) -> float:
        top, total = self.features(text)
        return 1 / (1 + math.exp(-(self.bias + self.by_max * top + self.by_sum * total)))


QUOTES = frozenset('"“”«»')


def held_out(id_col: Column) -> Column:
    return F.coalesce(F.crc32(id_col.cast("string")) % FOLDS == 0, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", most: int = MAX_TRAIN) -> DataFrame:
    """-> ``id``, ``text``, ``toxic`` of at most about ``most`` labelled documents outside the held-out fold, taken by hash."""
    known = labels.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull() & ~held_out(F.col(id_col)))
    known = known.groupBy(F.col(id_col).alias("id")).agg(F.max(F.col(label_col)).cast("int").alias("toxic"))
    share = most / max(1, known.count())
    if share < 1:
        known = known.where(F.pmod(F.xxhash64("id"), F.lit(1_000_000)) < int(share * 1_000_000))
    known = materialize(known, "labels")
    return docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text")).join(F.broadcast(known), "id")


def learn_lexicon(rows: DataFrame) -> tuple[dict, dict]:
    """Words and stems (token longer than the stem) tied to the toxic label, with weights near 1 for the surest.

    Features that the same documents have are gathered as one, with the numbers of those documents; the driver gets those
    whose likelihood ratio passes, fewer than the distinct words of at most MAX_TRAIN documents.
    """
    tokens = rows.select("id", "toxic", F.explode(F.array_distinct(F.split(F.lower("text"), "[^\\p{L}\\p{N}']+"))).alias("t")).where("length(t) >= 3")
    stem = [F.when(F.length("t") > n, F.concat(F.substring("t", 1, n), F.lit("*"))) for n in STEMS]
    features = tokens.select("id", "toxic", F.explode(F.array(F.col("t"), *stem)).alias("f")).where("f is not null").distinct()
    toxic = {r.id: r.toxic for r in rows.select("id", "toxic").distinct().collect()}  # MAX_TRAIN or so
    a_all, b_all = sum(toxic.values()), len(toxic) - sum(toxic.values())
    if not a_all or not b_all:
        return {}, {}
    counts = features.groupBy("f").agg(F.sum("toxic").alias("a"), F.sum(1 - F.col("toxic")).alias("b"))
    counts = materialize(counts.where("a + b >= 2"), "features")
    bar = 2 * math.log(max(2, counts.count())) + 2
    n, p = a_all + b_all, a_all / (a_all + b_all)
    seen = F.col("a") + F.col("b")
    ratio = F.col("a") / seen
    log = lambda x, y: F.when(x > 0, x * F.log(x / y)).otherwise(0.0)
    rest_a, rest_b = a_all - F.col("a"), b_all - F.col("b")
    g2 = 2 * (log(F.col("a"), seen * p) + log(F.col("b"), seen * (1 - p)) + log(rest_a, (n - seen) * p) + log(rest_b, (n - seen) * (1 - p)))
    picked = materialize(counts.where((g2 >= bar) & (ratio >= 0.35)), "picked")
    named = features.join(F.broadcast(picked), "f").groupBy("f", "a", "b").agg(F.sort_array(F.collect_list("id")).alias("ids"))
    is_stem = F.col("f").endswith("*")
    # a sure whole word stays whatever else its documents have; of others with equal documents the first in order stands for all
    sure = ~is_stem & (F.col("a") >= 0.9 * seen)
    order = F.struct(is_stem.alias("stem"), (-F.length("f")).alias("short"), "f")
    held = named.groupBy("ids", "a", "b", sure.alias("sure")).agg(F.min(order).alias("first"), F.collect_list(F.when(sure, F.col("f"))).alias("words")).collect()
    words, stems, covered = {}, {}, set()
    # surest first, then most frequent, then longest; a stem, or a word that clean texts have too, must still tell
    # something where no surer feature is
    for r in sorted(held, key=lambda r: (-r.a / (r.a + r.b), -r.a, tuple(r.first))):
        strength = (INSULT, round(((r.a + 0.1) / (r.a + r.b + 0.2)) ** 4, 3))
        left = [toxic[i] for i in r.ids if i not in covered]
        ra = sum(left)
        rb = len(left) - ra
        if not r.sure and (ra + rb == 0 or ra <= rb * 0.5 or 2 * ra * math.log(ra / ((ra + rb) * p)) < bar):
            continue
        for f in r.words if r.sure else [r.first.f]:
            (stems if f.endswith("*") else words)[f.rstrip("*")] = strength
        covered.update(r.ids)
    return words, stems


def fit_logistic(x: np.ndarray, y: np.ndarray, n: np.ndarray, prior: tuple, ridge: float = 0.05, steps: int = 60) -> tuple:
    """Weighted logistic regression by Newton steps, drawn toward ``prior``."""
    x = np.column_stack([np.ones(len(x)), x])
    w0 = w = np.array(prior, float)
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (n * (p - y)) + ridge * (w - w0)
        h = (x * (n * p * (1 - p) + 1e-9)[:, None]).T @ x + ridge * np.eye(x.shape[1])
        step = np.linalg.solve(h, grad)
        w = w - step
        if abs(step).max() < 1e-8:
            break
    return tuple(float(v) for v in w)


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", most: int = MAX_TRAIN) -> Model:
    rows = materialize(training_rows(docs, labels, id_col, text_col, label_col, most), "train")
    words, stems = learn_lexicon(rows)
    model = Model({w: (INSULT, 1.0) for w in SEED_INSULTS} | words, stems)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model)
        for batch in batches:
            f = [scorer.features(t.as_py()) for t in batch.column(0)]
            yield pa.RecordBatch.from_arrays([pa.array([round(v[i], 1) for v in f], pa.float64()) for i in (0, 1)] + [batch.column(1)], names=["top", "total", "toxic"])

    points = rows.select("text", "toxic").mapInArrow(run, "top double, total double, toxic int").groupBy("top", "total", "toxic").count().collect()
    if points:
        data = np.array([(r.top, r.total, r.toxic, r["count"]) for r in points], float)
        model.coefficients = fit_logistic(data[:, :2], data[:, 2], data[:, 3], model.coefficients)
    return model


def with_scores(docs: DataFrame, model: Model, text_col: str = "text", out: str = "score") -> DataFrame:
    """Add ``out``, the score of the whole text, to the rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model)
        for batch in batches:
            scores = [scorer.score(t.as_py()) for t in batch.column(text_col)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores, pa.float64())], names=[*batch.schema.names, out])

    schema = f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in docs.schema)}, `{out}` double"
    return docs.mapInArrow(run, schema)


def reject(docs: DataFrame, model: Model, text_col: str = "text", bar: float = 0.5) -> DataFrame:
    """The documents that score under ``bar``, their columns unchanged."""
    out = free_name(docs.columns, "score")
    return with_scores(docs, model, text_col, out).where(F.col(out) < bar).select(*[F.col(f"`{c}`") for c in docs.columns])
