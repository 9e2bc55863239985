"""Mixing sources to target weights with soft domain membership.

A classifier learned from a labelled table gives each document a posterior over domains. Nonnegative rates r_d
(how often a document is to be used) are fitted so that the expected tokens of each domain, the sum of
r_d * tokens_d * posterior_d, come as near to target shares of the total as can be: least squares over r >= 0 by projected
gradient steps from r = 1.

The gradient of half the squared residual is, per token of a document, the product of its posterior with the K residuals, so all
steps taken so far sum up to K numbers u, and the projected iterate is r_d = max(0, 1 - posterior_d . u). A step's length and
direction in those K numbers come from the second derivative over the documents not held at the bound (with a small weight on
staying near 1, lowered in TIES, which picks one of many optima); several lengths are tried in the same pass and the best one is taken. A step is
one pass over a narrow table of K numbers a document; nothing is rewritten and only sums over K domains reach the driver.

Targets that no rates can reach (a share beyond every document's posterior) end at the plain least-squares optimum;
the report's last entry has the remaining miss of each domain, and ``mix`` warns of it. A run that doesn't settle raises an error.
Rates have no upper bound.

Only DataFrame and SQL functions. The classifier is naive Bayes over hashed words (BUCKETS of them, counts from at most
MAX_TRAIN labelled documents chosen by hash); posteriors are tempered by the number of words. At most MAX_DOMAINS domains, as
their tables of evidence travel in the plan.

Defined cases: null text is empty; an empty text has the class priors as posterior and no tokens, its rate is 1; a
document with several labels counts for its smallest label; rows whose label or id is null are not learned from;
repeated rows are documents of their own; without labels, or without any token, all rates are 1; targets that are
negative or all zero raise an error; columns of any name may stand beside the id and the text.
"""

from __future__ import annotations

import json
import warnings

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name, materialize, small, text_of

BUCKETS, MAX_TRAIN, MAX_DOMAINS = 1 << 12, 4000, 64
#: Weights of staying near rate 1, one fit after the other; steps at most for each; step lengths tried in a pass; gradient (in
#: shares of the tokens) at which a fit has settled, and that a fit must reach.
TIES, STEPS, LENGTHS, SETTLED, ENOUGH = (1e-3, 1e-5, 1e-7), 40, (1.0, 0.5, 0.25, 0.1, 0.03, 0.01, 1e-3, 1e-4), 1e-8, 1e-5
#: Share of the tokens by which targets may be missed without a warning.
MISS = 1e-3
WORDS = "[ \\t\\n\\x0B\\f\\r]+"


def bucket_of(term: Column) -> Column:
    return F.pmod(F.xxhash64(term), F.lit(BUCKETS)).cast("int")


def words_of(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), WORDS), lambda w: w != "")


def learn(docs: DataFrame, labelled: DataFrame, id_col: str, text_col: str, label_col: str, most: int = MAX_TRAIN) -> tuple[list, np.ndarray, np.ndarray]:
    """-> domains, log priors (K), log likelihoods (BUCKETS x K), in units of bits of evidence a word."""
    known = labelled.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull())
    known = known.groupBy(F.col(id_col).alias("id")).agg(F.min(label_col).alias("domain"))
    totals = {r.domain: r["count"] for r in known.groupBy("domain").count().collect()}
    domains = sorted(totals)
    if not domains:
        return [], np.zeros(0), np.zeros((BUCKETS, 0))
    if len(domains) > MAX_DOMAINS:
        raise ValueError(f"{len(domains)} domains; at most {MAX_DOMAINS}")
    share = most / sum(totals.values())
    if share < 1:
        known = known.where(F.pmod(F.xxhash64("id"), F.lit(1_000_000)) < int(share * 1_000_000))
    known = materialize(known, "domains")
    rows = docs.select(F.col(id_col).alias("id"), text_of(text_col).alias("text")).join(F.broadcast(known), "id")
    counts = rows.select("domain", F.explode(F.array_distinct(F.transform(words_of(F.col("text")), bucket_of))).alias("b")).groupBy("domain", "b").count()
    n = np.zeros((BUCKETS, len(domains)))
    for r in counts.collect():  # at most BUCKETS x K sums
        n[r.b, domains.index(r.domain)] = r["count"]
    like = np.log((n + 0.5) / (n.sum(0) + 0.5 * BUCKETS))
    prior = np.log(np.array([totals[d] for d in domains], float) / sum(totals.values()))
    return domains, prior, like


def posteriors(docs: DataFrame, text_col: str, prior: np.ndarray, like: np.ndarray, temper: float = 0.5) -> DataFrame:
    """Add ``tokens`` and ``posterior`` (array of K). The evidence of n distinct words is scaled by n ** -temper."""
    k = len(prior)
    # evidence against the mean over domains, as integers of 1/1000, one array entry for each bucket and domain
    centred = np.rint(1000 * (like - like.mean(1, keepdims=True))).astype(int)
    tables = [F.from_json(F.lit(json.dumps(centred[:, j].tolist())), "array<int>") for j in range(k)]
    w = words_of(text_of(text_col))
    docs = docs.withColumn("tokens", F.size(w).cast("long")).withColumn("b__", F.array_distinct(F.transform(w, bucket_of)))
    n = F.greatest(F.lit(1), F.size("b__"))

    def evidence(j: int) -> Column:
        return F.aggregate("b__", F.lit(0).cast("long"), lambda s, b: s + F.get(tables[j], b)) / 1000.0

    logs = [F.lit(float(prior[j])) + evidence(j) / F.pow(n, F.lit(temper)) for j in range(k)]
    docs = docs.withColumn("l__", F.array(*logs))
    top = F.array_max("l__")
    docs = docs.withColumn("e__", F.transform("l__", lambda x: F.exp(x - top)))
    total = F.aggregate("e__", F.lit(0.0), lambda s, x: s + x)
    return docs.withColumn("posterior", F.transform("e__", lambda x: x / total)).drop("b__", "l__", "e__")


def rate_of(posterior: str, u: np.ndarray) -> Column:
    """The projected iterate: max(0, 1 - posterior . u); 1 for documents without tokens, which no step moves."""
    return F.when(F.col("tokens") == 0, 1.0).otherwise(step_of(posterior, u))


def step_of(posterior: str, u: np.ndarray) -> Column:
    return F.greatest(F.lit(0.0), F.lit(1.0) - sum((F.get(posterior, F.lit(j)) * F.lit(float(x)) for j, x in enumerate(u)), F.lit(0.0)))


def evaluate(weights: DataFrame, points: list[np.ndarray], target: np.ndarray, total: float, tie: float) -> tuple[list[float], np.ndarray, np.ndarray]:
    """In one pass: the objective at each u, and for the first the domains' shares and the second derivative (shares of ``total`` tokens)."""
    k = len(target)
    p = [F.get("posterior", F.lit(j)) for j in range(k)]
    r = step_of("posterior", points[0])
    sums = [F.sum(F.col("tokens") * x * x) for x in (step_of("posterior", u) for u in points)]
    sums += [F.sum(F.col("tokens") * r * x) for x in p]
    sums += [F.sum(F.when(r > 0, F.col("tokens") * p[i] * p[j])) for i in range(k) for j in range(i + 1)]
    flat = np.array([x or 0.0 for x in weights.agg(*sums).first()], float) / total
    n = len(points)
    curve = np.zeros((k, k))
    curve[np.tril_indices(k)] = flat[n + k :]
    curve = curve + np.tril(curve, -1).T + tie * np.eye(k)
    return [float(v / 2 + target @ u + tie / 2 * (u @ u)) for v, u in zip(flat[:n], points, strict=True)], flat[n : n + k], curve


def fit_rates(weights: DataFrame, shares: dict | list, steps: int = STEPS) -> tuple[Column, list[dict]]:
    """``tokens``, ``posterior`` (materialized) -> the rate as a column expression, and a report for each step."""
    target = np.array(list(shares), float)
    if (target < 0).any() or not target.sum() > 0:
        raise ValueError("targets must be nonnegative and not all zero")
    target /= target.sum()
    total = float(weights.agg(F.coalesce(F.sum("tokens"), F.lit(0))).first()[0])
    if not total:
        return F.lit(1.0), []

    def best_of(points: list[np.ndarray], tie: float) -> tuple:
        """The point with the least objective, and what the next step needs there: one pass if it is the first, else two."""
        values, got, curve = evaluate(weights, points, target, total, tie)
        at = int(np.argmin(values))
        if at:
            _, got, curve = evaluate(weights, [points[at]], target, total, tie)
        return (values[at], got, curve), points[at]

    u, report, before = np.zeros(len(target)), [], None
    for tie in TIES:
        # what a target out of reach leaves is tie * u, what is within reach leaves u as it is
        (value, got, curve), u = best_of([u] if before is None else [u, u * (before / tie)], tie)
        before = tie
        for _ in range(steps):
            gradient = target + tie * u - got
            report.append({"tie": tie, "miss": float(np.abs(got - target).sum()), "missed": (target - got).tolist(), "gradient": float(np.abs(gradient).max())})
            if report[-1]["gradient"] <= SETTLED:
                break
            way = -np.linalg.solve(curve, gradient)
            (new, got_there, curve_there), at = best_of([u + x * way for x in LENGTHS], tie)
            if new >= value and np.abs(target + tie * at - got_there).max() >= report[-1]["gradient"]:
                break  # the last digits of the sums: no step is better any more
            value, got, curve, u = new, got_there, curve_there, at
    if report[-1]["gradient"] > ENOUGH:
        raise RuntimeError(f"rates did not settle: {report[-1]}")
    return rate_of("posterior", u), report


def copies(rate: Column, id_col: Column) -> Column:
    """Whole uses of a document: the rate rounded up or down by the id's hash, so that totals are kept on average."""
    u = F.pmod(F.xxhash64(id_col, F.lit("mix")), F.lit(1 << 20)) / F.lit(float(1 << 20))
    return F.floor(rate + u).cast("int")


def mix(docs: DataFrame, labelled: DataFrame, shares: dict, id_col: str = "doc_id", text_col: str = "text", label_col: str = "domain") -> tuple[DataFrame, list, list[dict]]:
    """-> (``id_col``, ``tokens``, ``posterior``, ``rate``), domains, report. ``shares``: domain -> target weight (0 if absent)."""
    domains, prior, like = learn(docs, labelled, id_col, text_col, label_col)
    if not domains:
        flat = docs.select(id_col, F.size(words_of(text_of(text_col))).cast("long").alias("tokens"), F.array(F.lit(1.0)).alias("posterior"), F.lit(1.0).alias("rate"))
        return flat, [], []
    weights = materialize(posteriors(docs.select(F.col(id_col), F.col(text_col).alias("text__")), "text__", prior, like).select(id_col, "tokens", "posterior"), "posteriors")
    rate, report = fit_rates(weights, [shares.get(d, 0.0) for d in domains])
    if report and report[-1]["miss"] > MISS:
        warnings.warn(f"no rates reach the targets; shares still missing: {dict(zip(domains, report[-1]['missed'], strict=True))}", stacklevel=2)
    return weights.withColumn("rate", rate), domains, report


def labelled_domains(labels: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The labels table's domains: ``toxic``, else ``junk`` (quality 0) or ``sound`` (quality 1)."""
    domain = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 0, "junk").when(F.col("quality") == 1, "sound")
    return labels.select(id_col, domain.alias("domain"))


def resample(docs: DataFrame, rates: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The documents as often as their ``rate`` says; ``docs`` and ``rates`` have the same rows of ids.

    Rows with a null id are used once each time their own rate rounds up to.
    """
    key, n, k = (free_name(docs.columns, x) for x in ("id", "n", "k"))
    times = rates.groupBy(id_col).agg(F.max("rate").alias("rate"))
    times = times.select(F.col(id_col).alias(key), copies(F.col("rate"), F.col(id_col)).alias(n))
    odd = small(materialize(times.where(F.col(n) != 1), "copies"), 24)
    joined = docs.join(odd, docs[id_col].eqNullSafe(odd[key]), "left").withColumn(n, F.coalesce(n, F.lit(1)))
    return joined.where(F.col(n) > 0).withColumn(k, F.explode(F.sequence(F.lit(1), F.col(n)))).select(*[docs[c] for c in docs.columns])
