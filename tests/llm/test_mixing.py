import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from tilerank.llm import mixing, registry


def table(spark, n=300):
    rnd = random.Random(1)
    rows = []
    for i in range(n):
        d = "abc"[min(2, i % 5)]
        rows.append((i, " ".join(rnd.choice("abc"[: 1 + rnd.randrange(3)] if rnd.random() < 0.2 else d) + str(rnd.randrange(30)) for _ in range(rnd.randrange(5, 60))), d))
    return spark.createDataFrame(rows, "doc_id bigint, text string, domain string")


def test_rates_meet_targets_and_are_a_least_squares_optimum(spark):
    docs = table(spark)
    rates, domains, report = mixing.mix(docs, docs.select("doc_id", "domain"), {"a": 0.5, "b": 0.3, "c": 0.2})
    rows = rates.collect()
    a = np.array([[r.tokens * p for p in r.posterior] for r in rows])
    r = np.array([x.rate for x in rows])
    assert domains == ["a", "b", "c"] and (r >= 0).all()
    got, total = r @ a, a.sum()
    assert abs(got / total - [0.5, 0.3, 0.2]).max() < 1e-4 and report[0]["miss"] > report[-1]["miss"]


def plain_optimum(p, tokens, target, steps=40_000):
    """Residual of the least-squares optimum over nonnegative rates, by plain accelerated projected gradient in NumPy."""
    a = p * (tokens / tokens.sum())[:, None]
    size = np.linalg.norm(a, 2) ** 2
    r = z = np.ones(len(a))
    for k in range(steps):
        new = np.maximum(0, z - a @ (a.T @ z - target) / size)
        z, r = new + k / (k + 3) * (new - r), new
    return float(np.linalg.norm(a.T @ r - target))


def fitted(spark, p, tokens, target):
    rows = [(i, int(t), [float(x) for x in q]) for i, (q, t) in enumerate(zip(p, tokens))]
    weights = spark.createDataFrame(rows, "doc_id bigint, tokens bigint, posterior array<double>")
    rate, report = mixing.fit_rates(weights, target)
    got = {x.doc_id: x.r for x in weights.select("doc_id", rate.alias("r")).collect()}
    return np.array([got[i] for i in range(len(p))]), report


def test_reachable_and_unreachable_targets_end_at_the_plain_optimum(spark):
    rng = np.random.default_rng(3)
    tokens = rng.integers(5, 400, 300)
    for spread, target in ((0.3, [0.5, 0.3, 0.2]), (0.3, [0.9, 0.1, 0.0]), (6.0, [0.0, 0.1, 0.9]), (6.0, [1.0, 0.0, 0.0])):
        p = rng.dirichlet([spread * 3, spread, spread], 300)
        r, report = fitted(spark, p, tokens, target)
        share = (p * (tokens * r)[:, None]).sum(0) / tokens.sum()
        off = share - np.array(target)
        best = plain_optimum(p, tokens, np.array(target))
        assert (r >= 0).all() and abs(np.linalg.norm(off) - best) < 1e-3, (target, np.linalg.norm(off), best)
        assert np.allclose(report[-1]["missed"], -off, atol=1e-6) and report[-1]["gradient"] < 1e-5
        # no document with a rate could lower the residual, and none without one either
        slope = p @ off
        assert slope.min() > -1e-3 and abs((r * tokens / tokens.sum()) @ slope) < 1e-3


def test_a_step_is_a_projected_gradient_step(spark):
    """From rate 1, the first step tried goes against the gradient in the metric of the documents' second moments."""
    rng = np.random.default_rng(4)
    p, tokens, target = rng.dirichlet([0.6, 0.2, 0.2], 200), rng.integers(5, 400, 200), np.array([0.5, 0.3, 0.2])
    r, report = fitted(spark, p, tokens, target)
    w = tokens / tokens.sum()
    u, steps, before = np.zeros(3), 0, None
    for tie in mixing.TIES:
        value = lambda x, tie=tie: 0.5 * (w * np.maximum(0, 1 - p @ x) ** 2).sum() + target @ x + tie / 2 * x @ x
        u = u if before is None else min((u, u * (before / tie)), key=value)
        before = tie
        while True:
            r0 = np.maximum(0, 1 - p @ u)
            gradient = target + tie * u - (w * r0) @ p
            steps += 1
            if abs(gradient).max() <= mixing.SETTLED:
                break
            curve = (p * (w * (r0 > 0))[:, None]).T @ p + tie * np.eye(3)
            way = -np.linalg.solve(curve, gradient)
            u = min((u + x * way for x in mixing.LENGTHS), key=value)
    assert np.allclose(r, np.maximum(0, 1 - p @ u), atol=1e-6) and len(report) == steps


def test_posteriors_equal_brute_force(spark):
    docs = table(spark, 40)
    domains, prior, like = mixing.learn(docs, docs.select("doc_id", "domain"), "doc_id", "text", "domain")
    rows = mixing.posteriors(docs, "text", prior, like).withColumn("b", F.array_distinct(F.transform(mixing.words_of(F.col("text")), mixing.bucket_of))).collect()
    c = np.rint(1000 * (like - like.mean(1, keepdims=True)))
    for r in rows:
        logs = prior + c[r.b].sum(0) / 1000 / math.sqrt(len(r.b))
        p = np.exp(logs - logs.max())
        assert np.allclose(r.posterior, p / p.sum()) and r.tokens == len(r.text.split())
    assert sum(domains[int(np.argmax(r.posterior))] == r.domain for r in rows) >= 36


def test_defined_cases(spark):
    docs = spark.createDataFrame([(1, None, 1), (2, "", 2), (None, "x y", 3), (4, "x y", 4), (4, "x y", 4), (5, "word " * 50_000, 5)], "doc_id bigint, text string, rate int")
    labels = spark.createDataFrame([(4, "p"), (4, "o"), (5, "p"), (None, "p"), (1, None)], "doc_id bigint, domain string")
    rates, domains, _ = mixing.mix(docs, labels, {"o": 0.5, "p": 0.5})
    rows = rates.collect()
    assert domains == ["o", "p"] and len(rows) == 6 and all(r.rate == 1 for r in rows if r.tokens == 0)
    assert mixing.resample(docs, rates).columns == docs.columns
    clash = docs.select("*", *[F.lit(i).alias(c) for i, c in enumerate(["id", "n", "k", "n__", "k__", "id__", "tokens", "posterior", "b__", "text__"])])
    again, _, _ = mixing.mix(clash, labels, {"o": 0.5, "p": 0.5})
    assert sorted(r.rate for r in again.collect()) == sorted(r.rate for r in rows)
    used = mixing.resample(clash, again)
    assert used.columns == clash.columns and all(r.k__ == 4 and r.tokens == 6 for r in used.collect())
    for bad in ({"o": -1.0, "p": 1.0}, {}):
        with pytest.raises(ValueError):
            mixing.mix(docs, labels, bad)
    none, d, _ = mixing.mix(docs, labels.limit(0), {})
    assert d == [] and all(r.rate == 1 for r in none.collect())
    assert mixing.mix(docs.limit(0), labels, {"o": 1.0})[0].count() == 0


def test_resampling_follows_the_rates(spark):
    docs = spark.range(4000).select(F.col("id").alias("doc_id"), F.lit("t").alias("text"))
    rates = docs.select("doc_id", (F.col("doc_id") % 4 * 0.75).alias("rate"))
    got = {r.doc_id: r["count"] for r in mixing.resample(docs, rates).groupBy("doc_id").count().collect()}
    for k in range(4):
        assert abs(sum(got.get(i, 0) for i in range(k, 4000, 4)) / 1000 - 0.75 * k) < 0.06
    assert not any(i % 4 == 0 for i in got)


def test_query(spark, sf):
    rows = registry.op1_mixing(spark, sf).collect()
    total = sum(r.tokens for r in rows)
    assert abs(sum(r.rate * r.tokens * r.p_sound for r in rows) / total - 0.85) < 0.01
    assert all(abs(r.p_sound + r.p_junk + r.p_toxic - 1) < 1e-9 for r in rows)


def test_a_rare_domain_reaches_its_target(spark):
    rows = [(i, 10, [1.0, 0.0]) for i in range(300)] + [(300, 10, [0.0, 1.0])]
    weights = spark.createDataFrame(rows, "doc_id bigint, tokens bigint, posterior array<double>")
    rate, report = mixing.fit_rates(weights, [0.9, 0.1])
    got = {r.doc_id: r.r for r in weights.select("doc_id", rate.alias("r")).collect()}
    assert abs(got[300] - 30.1) < 1e-3 and report[-1]["miss"] < 1e-4, report[-1]


def test_a_miss_is_told(spark):
    docs = spark.createDataFrame([(i, "a b c" if i % 2 else "a b d", "x" if i % 2 else "y") for i in range(40)], "doc_id bigint, text string, domain string")
    with pytest.warns(UserWarning, match="no rates reach"):
        mixing.mix(docs, docs.select("doc_id", "domain"), {"x": 1.0, "y": 0.0})
