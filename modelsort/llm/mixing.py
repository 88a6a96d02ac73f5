"""Mixing to target weights by soft membership, in DataFrame functions only.

A naive Bayes classifier over hashed words, learned from a labelled table, gives
every document a posterior over domains. Every document then has a rate, 1 to
begin with, and rates are fitted so that the expected tokens of each domain, the
sum of rate x tokens x posterior, meet their targets: projected gradient descent
on half the squared miss over rates of 0 or more. A step moves each rate along its own
gradient, its tokens times the posterior-weighted miss, and clips it at 0. Domains
are scaled by the Gram matrix of the documents whose rates can follow the gradient
(those above 0 or drawn upwards); plain steps of several lengths are tried along
with it. One aggregate gives that matrix, another the outcome of all trials, and
the best is taken. Rates are written every few steps and carried as an expression
in between.
"""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.functions.literals import double_array
from modelsort.plans.durable import materialize

#: Labelled documents that the classifier learns from at most.
TRAIN_DOCS = 10_000
#: Words are hashed to so many numbers, which bounds the table of likelihoods that tasks get.
BUCKETS = 1 << 17
SMOOTHING = 0.5
SPACE = r"[ \t\n\x0B\f\r]+"
#: A fit that hasn't come to rest after so many steps says so.
MOST_STEPS = 40
TOLERANCE = 1e-9
#: A step that gains no larger share of the objective is the last.
STALLED = 1e-10
#: Steps that a rate is carried as an expression before it is written.
WRITE_EVERY = 4
#: Lengths tried of the scaled step, and of the plain one in units of the length that is safe for any rates.
SCALED, PLAIN = (1.0, 0.5, 0.1, 0.01), (1.0, 100.0)


def words(text: Column) -> Column:
    """Lower-cased pieces of the text between runs of white space; none for a blank text."""
    return F.filter(F.split(F.lower(text), SPACE, -1), lambda word: word != "")


@dataclass
class Domains:
    """Domain names, their log priors, and log likelihoods by hashed word, at most ``BUCKETS`` rows."""

    names: list[str]
    priors: list[float]
    likelihoods: DataFrame


def _bucket(word: Column) -> Column:
    return F.pmod(F.xxhash64(word), F.lit(BUCKETS)).cast("int")


def learn_domains(docs: DataFrame, labelled: DataFrame, n: int = TRAIN_DOCS, id_col: str = "doc_id", text_col: str = "text") -> Domains:
    """Classifier of ``labelled`` (columns ``doc_id, domain``) from the texts of at most ``n`` ids, those of least hash.

    Null ids, domains and texts teach nothing; an id with several domains counts
    as the least; repeated rows teach again. Fewer than one domain gives a classifier that is always unsure.
    """
    known = labelled.select(F.col("doc_id").cast("long").alias("__id"), F.col("domain").cast("string").alias("domain")).where("__id is not null and domain is not null")
    chosen = known.groupBy("__id").agg(F.min("domain").alias("domain")).orderBy(F.xxhash64("__id"), "__id").limit(n)
    sample = docs.select(F.col(id_col).cast("long").alias("__id"), F.col(text_col).cast("string").alias("text")).where("text is not null").join(F.broadcast(chosen), "__id")
    counts = materialize(sample.select("domain", F.explode(words(F.col("text"))).alias("word")).groupBy("domain", _bucket(F.col("word")).alias("word")).count(), "domain-words")
    sizes = {r["domain"]: r["words"] for r in counts.groupBy("domain").agg(F.sum("count").alias("words")).collect()}  # a row a domain
    names = sorted(sizes)
    total = sum(sizes.values())
    table = counts.groupBy("word").agg(F.sum("count").alias("n"), *(F.sum(F.when(F.col("domain") == name, F.col("count")).otherwise(0)).alias(f"n{j}") for j, name in enumerate(names)))
    likelihood = lambda j, name: F.log((F.col(f"n{j}") + SMOOTHING) / (sizes[name] + SMOOTHING * BUCKETS))
    frame = materialize(table.select("word", *(likelihood(j, name).alias(f"l{j}") for j, name in enumerate(names))), "domain-likelihoods")
    priors = [float(np.log(sizes[name] / total)) for name in names]
    return Domains(names, priors, frame)


def memberships(docs: DataFrame, domains: Domains, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Columns ``doc_id, tokens, p`` of each id: whole-text words and the posterior array, in the order of names.

    Null, empty and blank texts have no tokens and the prior as posterior. Rows that
    repeat an id count together; rows without id are taken together by their text.
    An empty table gives none. Words that no labelled text hashes to tell nothing.
    """
    text = F.when(F.length(text_col) > 0, F.col(text_col).cast("string"))
    nameless = F.when(F.col(id_col).isNull(), F.xxhash64(text))  # keeps rows without id out of one group
    each = docs.select(F.col(id_col).cast("long").alias("doc_id"), nameless.alias("__text"), F.explode_outer(words(text)).alias("__word")).withColumn("word", _bucket(F.col("__word")))
    rated = each.join(F.broadcast(domains.likelihoods), "word", "left")
    names = range(len(domains.names))
    sums = rated.groupBy("doc_id", "__text").agg(F.count("__word").alias("tokens"), *(F.coalesce(F.sum(f"l{j}"), F.lit(0.0)).alias(f"s{j}") for j in names))
    logits = F.array(*(F.lit(domains.priors[j]) + F.col(f"s{j}") for j in names)) if domains.names else F.array().cast("array<double>")
    odds = F.transform("logits", lambda x: F.exp(x - F.array_max("logits")))
    total = F.aggregate("odds", F.lit(0.0), lambda a, x: a + x)
    return sums.withColumn("logits", logits).withColumn("odds", odds).select("doc_id", "tokens", F.transform("odds", lambda x: x / total).alias("p"))


@dataclass
class Fit:
    """Targets and fitted totals by domain, half the squared miss after each step, and whether the fit met its tolerance."""

    targets: list[float]
    totals: list[float]
    objectives: list[float]
    converged: bool


def _along(direction: np.ndarray) -> Column:
    """Posterior times a direction. Its numbers are read from an array, so that code compiled for one step serves the next."""
    numbers = double_array(direction)
    return sum((F.col("p")[j] * numbers[j] for j in range(len(direction))), F.lit(0.0))


def _stepped(rate: Column, direction: np.ndarray) -> Column:
    """A rate after a step: less its tokens times the posterior-weighted direction, at least 0."""
    return F.greatest(F.lit(0.0), rate - F.col("tokens") * _along(direction))


def fit_rates(members: DataFrame, names: list[str], weights: Mapping[str, float] | None = None, budget: float | None = None, tolerance: float = TOLERANCE) -> tuple[DataFrame, Fit]:
    """``members`` with the fitted ``rate``, for token targets ``weights[name] * budget``; by default equal weights and all tokens.

    Domains missing in ``weights`` get 0. Targets that no rates of 0 or more can
    meet are met as closely as such rates can. The fit has converged when the miss is within the tolerance or no step gains any more; otherwise ``converged`` is false. A corpus without tokens keeps rate 1.
    """
    d = len(names)
    weights = weights or dict.fromkeys(names, 1.0)
    scale = sum(max(0.0, weights.get(n, 0.0)) for n in names)
    tokens, p = F.col("tokens").cast("double"), F.col("p")
    members = members.withColumn("rate", F.lit(1.0))
    if not d:
        return members, Fit([], [], [], True)
    square = F.aggregate(p, F.lit(0.0), lambda a, x: a + x * x)
    first = members.agg(F.sum(tokens), F.sum(tokens * tokens * square), *(F.sum(tokens * p[j]) for j in range(d))).first()
    n_tokens, trace, totals = float(first[0] or 0.0), float(first[1] or 0.0), np.array([float(x or 0.0) for x in first[2:]])
    budget = n_tokens if budget is None else budget
    targets = np.array([max(0.0, weights.get(n, 0.0)) for n in names]) / (scale or 1.0) * budget
    miss = totals - targets
    objectives, converged = [float(miss @ miss) / 2], False
    if not n_tokens:
        return members, Fit(targets.tolist(), totals.tolist(), objectives, True)
    floor = (tolerance * max(budget, 1.0)) ** 2 / 2
    rate, carried = F.col("rate"), 0
    for _ in range(MOST_STEPS):
        if objectives[-1] <= floor:
            converged = True
            break
        gradient = _along(miss)
        weight = F.when((rate > 0) | (gradient < 0), tokens * tokens).otherwise(0.0)
        half = members.agg(*(F.sum(weight * p[i] * p[j]) for i in range(d) for j in range(i, d))).first()
        gram = np.zeros((d, d))
        gram[np.triu_indices(d)] = [float(x) for x in half]
        scaled = np.linalg.pinv(gram + np.triu(gram, 1).T, rcond=1e-12) @ miss
        tries = [x * scaled for x in SCALED] + [x / trace * miss for x in PLAIN]
        sums = members.agg(*(F.sum(_stepped(rate, v) * tokens * p[j]) for v in tries for j in range(d))).first()
        after = np.array([float(x) for x in sums]).reshape(len(tries), d)
        left = np.square(after - targets).sum(axis=1) / 2
        best = int(left.argmin())
        if left[best] >= objectives[-1] * (1 - STALLED):
            converged = True
            break
        rate, miss, totals, carried = _stepped(rate, tries[best]), after[best] - targets, after[best], carried + 1
        objectives.append(float(left[best]))
        if carried == WRITE_EVERY:
            members, rate, carried = materialize(members.withColumn("rate", rate), "rates"), F.col("rate"), 0
    return members.withColumn("rate", rate), Fit(targets.tolist(), totals.tolist(), objectives, converged)


def copies(rate: Column, doc_id: Column) -> Column:
    """Whole copies whose expectation over ids is the rate, the same on every run."""
    part = F.pmod(F.xxhash64(doc_id, F.lit("copies")), F.lit(1 << 30)) / F.lit(float(1 << 30))
    return (F.floor(rate) + F.when(part < rate - F.floor(rate), 1).otherwise(0)).cast("long")


def mix(docs: DataFrame, labelled: DataFrame, weights: Mapping[str, float] | None = None, budget: float | None = None, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, Fit, list[str]]:
    """Columns ``doc_id, tokens, domain, rate, copies`` of each id, the fit, and the domain names."""
    domains = learn_domains(docs, labelled, id_col=id_col, text_col=text_col)
    members = materialize(memberships(docs, domains, id_col, text_col), "memberships")
    fitted, found = fit_rates(members, domains.names, weights, budget)
    names = F.array(*(F.lit(n) for n in domains.names)) if domains.names else F.array().cast("array<string>")
    best = F.try_element_at(names, F.array_position("p", F.array_max("p")).cast("int")) if domains.names else F.lit(None).cast("string")
    rated = fitted.select("doc_id", "tokens", best.alias("domain"), "rate", copies(F.col("rate"), F.col("doc_id")).alias("copies"))
    return rated, found, domains.names
