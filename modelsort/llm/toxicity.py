"""Toxicity by maximum-scoring segments.

A token is a word or one of its leading strings, so that the forms of a stem share
evidence. Every token has a signed score: its log-odds between toxic and clean
labelled texts that hold it, repeats within a text apart, under an informative
Dirichlet prior, brought nearer to 0 by a number of its own standard errors. A word
takes the strongest score among its tokens, less a constant drift. One linear
scan gives all maximal scoring segments of a text. Scores of best segments of
clean texts follow an extreme-value law; its two constants (the decay from the
distribution of word scores in clean texts, the size factor from their best
segments) turn a segment's score into an expected number of chance segments. A
logistic fit of the text's best and total significance gives the probability.

All that is fitted on segments is fitted on texts whose fold had no part in the
token scores they were found with. ``PRIOR_SHARE``, ``SHRINK`` and ``DRIFT`` come from
``cross_validate`` on the learning folds: the least drift whose loss is within a
standard error (0.003) of the least.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.llm.bytetext import HashIndex, blocks, row_sums, utf8_view, word_bounds, word_hashes
from modelsort.llm.langid import fold
from modelsort.llm.samples import free_name, labelled_sample, quoted
from modelsort.plans.durable import materialize

#: Labelled documents that the model is fitted on at most.
TRAIN_DOCS = 20_000
#: Folds that labels are learned from; fold 0 is held out.
FOLDS = (1, 2, 3, 4)
#: Weight of the Dirichlet prior against the labelled texts' own counts.
PRIOR_SHARE = 0.02
#: Standard errors by which a score is brought nearer to 0.
SHRINK = 2.0
DRIFT = 1.0
#: Decays between which the extreme-value law's own is looked for.
DECAYS = np.geomspace(0.05, 12.0, 28)
SIGNIFICANT = 0.05
#: Lengths in bytes of the leading strings that count as tokens, where they end with a character.
STEMS = (4, 5, 6, 7, 8, 9)
EULER = 0.5772156649015329

SEGMENT_DDL = "array<struct<start:long,stop:long,score:double,expected:double>>"
RESULT_DDL = f"score double, n_words long, segments {SEGMENT_DDL}"
RESULT = pa.struct([("score", pa.float64()), ("n_words", pa.int64()), ("segments", pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64()), ("score", pa.float64()), ("expected", pa.float64())])))])


def tokens(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of a block's words and their stems, folded to lower case, and the offsets of its texts among the words."""
    low = fold(data)
    starts, ends, bounds = word_bounds(low, offsets)
    return word_hashes(low, starts, ends, STEMS), bounds


def maximal_segments(places: list[int], befores: list[float], afters: list[float]) -> list[tuple[int, int, float]]:
    """All maximal scoring segments of a sequence, in one scan.

    ``places`` are the positions with a positive score, ``befores`` and ``afters``
    the running totals of all scores up to and with each. A stack holds
    candidates with their totals; a new candidate swallows those that it improves.
    """
    stack: list[tuple[int, int, float, float]] = []
    for place, before, after in zip(places, befores, afters, strict=True):
        start, stop = place, place + 1
        while stack:
            k = len(stack) - 1
            while k >= 0 and stack[k][2] >= before:
                k -= 1
            if k < 0 or stack[k][3] >= after:
                break
            start, before = stack[k][0], stack[k][2]
            del stack[k:]
        stack.append((start, stop, before, after))
    return [(a, b, after - before) for a, b, before, after in stack]


@dataclass
class Model:
    """Token scores, the extreme-value constants and the logistic weights."""

    lexicon: HashIndex
    scores: np.ndarray
    drift: float
    decay: float
    size_factor: float
    weights: np.ndarray

    def word_scores(self, hashes: np.ndarray) -> np.ndarray:
        """Score of each word: that of its strongest token, less the drift."""
        best = np.zeros(len(hashes))
        for k in range(hashes.shape[1]):
            found = self.lexicon.find(hashes[:, k])
            at = np.flatnonzero(found >= 0)
            value = self.scores[found[at]]
            stronger = np.abs(value) > np.abs(best[at])
            best[at[stronger]] = value[stronger]
        return best - self.drift

    def segments(self, data: np.ndarray, offsets: np.ndarray, word_scores: list | None = None) -> tuple[np.ndarray, list[list[tuple[int, int, float]]]]:
        """Words of each text and its maximal segments; scores of all words go to ``word_scores`` if it is given."""
        hashes, bounds = tokens(data, offsets)
        value = self.word_scores(hashes)
        if word_scores is not None:
            word_scores.append(value)
        total = np.cumsum(value)
        at = np.flatnonzero(value > 0)
        cut = np.searchsorted(at, bounds)
        out: list[list[tuple[int, int, float]]] = [[] for _ in range(len(bounds) - 1)]
        places, befores, afters = at.tolist(), (total[at] - value[at]).tolist(), total[at].tolist()
        for r in np.flatnonzero(np.diff(cut)).tolist():
            a, b, base = int(cut[r]), int(cut[r + 1]), int(bounds[r])
            found = maximal_segments(places[a:b], befores[a:b], afters[a:b])
            out[r] = [(s - base, e - base, v) for s, e, v in found]
        return np.diff(bounds), out

    def expected(self, score: float, words: int) -> float:
        """Chance segments of this score or more that a clean text of so many words would have."""
        return self.size_factor * words * math.exp(-min(self.decay * score, 700.0))

    def features(self, words: int, segments: list[tuple[int, int, float]]) -> list[float]:
        """Best and total significance in nats; a segment that chance explains adds nothing."""
        nats = [max(0.0, -math.log(max(self.expected(s, max(words, 1)), 1e-300))) for _, _, s in segments]
        return [1.0, math.log1p(max(nats, default=0.0)), math.log1p(sum(nats))]

    def score(self, rows: list[list[float]]) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(np.array(rows).reshape(-1, 3) @ self.weights, -30, 30)))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 25) -> np.ndarray:
    """Ridge logistic weights by Newton steps; the first column is the constant."""
    w = np.zeros(x.shape[1])
    penalty = np.full(x.shape[1], ridge)
    penalty[0] = 1e-3
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(penalty), x.T @ (y - p) - penalty * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts of a task that hold each token, by fold and class."""
    for batch in batches:
        data, offsets = utf8_view(batch.column("text"))
        group = 2 * np.searchsorted(FOLDS, batch.column("fold").to_numpy()) + (batch.column("label").to_numpy(zero_copy_only=False) == 1)
        for a, b in blocks(offsets):
            hashes, bounds = tokens(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
            row = np.repeat(np.repeat(np.arange(b - a), np.diff(bounds)), hashes.shape[1])
            used = hashes.ravel() != 0
            known, which = np.unique(hashes.ravel()[used], return_inverse=True)
            of = np.unique(which * np.int64(b - a) + row[used])
            found = np.bincount(of // (b - a) * 2 * len(FOLDS) + group[a:b][of % (b - a)], minlength=len(known) * 2 * len(FOLDS)).reshape(len(known), -1)
            yield pa.RecordBatch.from_arrays([pa.array(known.view(np.int64)), *(pa.array(c) for c in found.T.astype(np.int64))], names=["token", *COUNTS])


#: Texts with a token: clean and toxic ones of each learning fold.
COUNTS = [f"{name}{f}" for f in FOLDS for name in ("clean", "toxic")]


def token_scores(toxic: Column, clean: Column, n_toxic: Column, n_clean: Column, prior_share: float, shrink: float) -> Column:
    """Signed log-odds of tokens, ``shrink`` standard errors nearer to 0."""
    prior, mass = F.lit(prior_share) * (toxic + clean), F.lit(prior_share) * (n_toxic + n_clean)
    odds = lambda y, total: F.log(F.try_divide(y + prior, total + mass - y - prior))
    delta = odds(toxic, n_toxic) - odds(clean, n_clean)
    deviation = F.sqrt(F.try_divide(F.lit(1.0), toxic + prior) + F.try_divide(F.lit(1.0), clean + prior))
    sure = F.greatest(F.lit(0.0), F.abs(delta) - F.lit(shrink) * deviation)
    return F.when((toxic + clean > 0) & (n_toxic > 0) & (n_clean > 0), F.coalesce(F.signum(delta) * sure, F.lit(0.0))).otherwise(0.0)  # a token of every text tells nothing


def _decay(means: np.ndarray) -> float:
    """Positive root of the mean of exp(x * score) = 1, between the decays tried; 1 if all scores are alike."""
    logs = np.log(means)
    over = np.flatnonzero(logs >= 0)
    if not len(over) or not over[0]:
        return float(DECAYS[-1]) if not len(over) else 1.0
    k = over[0]
    share = logs[k - 1] / (logs[k - 1] - logs[k])
    return float(DECAYS[k - 1] + share * (DECAYS[k] - DECAYS[k - 1]))


def train(docs: DataFrame, labels: DataFrame, label: str = "toxic", n: int = TRAIN_DOCS, text_col: str = "text", prior_share: float = PRIOR_SHARE, shrink: float = SHRINK, drift: float = DRIFT) -> Model:
    """Model of ``label`` from at most ``n`` labelled documents outside fold 0.

    Without any toxic or any clean example the model has no lexicon and scores
    every text by the share of label 1, or 0 if there are no labels. Null texts
    are empty ones; columns beside id and text are not read.
    """
    return _train(docs, labels, label, n, text_col, prior_share, shrink, drift)[0]


def cross_validate(docs: DataFrame, labels: DataFrame, label: str = "toxic", n: int = TRAIN_DOCS) -> list[tuple[float, float, float, float]]:
    """Mean log loss on the learning folds, each scored without its own labels, by prior share, shrinkage and drift; best first."""
    grid = itertools.product((0.005, 0.02, 0.1), (1.0, 2.0, 3.0), (0.25, 0.5, 1.0, 1.5))
    return sorted((_train(docs, labels, label, n, "text", *choice)[1], *choice) for choice in grid)


def _train(docs: DataFrame, labels: DataFrame, label: str, n: int, text_col: str, prior_share: float, shrink: float, drift: float) -> tuple[Model, float]:
    """The model and its mean log loss on cross-fitted features."""
    spark = docs.sparkSession
    sample = materialize(labelled_sample(docs, labels, label, n, text_col=text_col), "toxicity-sample")
    counts = sample.mapInArrow(_count, "token long, " + ", ".join(f"{c} long" for c in COUNTS)).groupBy("token").agg(*(F.sum(c).alias(c) for c in COUNTS))
    counts = materialize(counts, "toxicity-counts")
    size = counts.agg(F.struct(*(F.sum(c).alias(c) for c in COUNTS)).alias("n")).first()["n"]

    def scores(folds: list[int]) -> Column:
        take = lambda name: sum((F.col(f"{name}{f}") for f in folds), F.lit(0))
        total = lambda name: F.lit(float(sum(size[f"{name}{f}"] or 0 for f in folds)))
        return token_scores(take("toxic"), take("clean"), total("toxic"), total("clean"), prior_share, shrink)

    # One lexicon for each fold without its own texts, and the final one of all.
    rated = counts.select("token", *(scores([g for g in FOLDS if g != f]).alias(f"s{f}") for f in FOLDS), scores(list(FOLDS)).alias("s0"))
    rows = rated.where(F.greatest(*(F.abs(f"s{f}") for f in (0, *FOLDS))) > 0).toPandas()  # tokens of the sample that tell something
    models = {}
    for f in (0, *FOLDS):
        told = rows[rows[f"s{f}"] != 0]
        models[f] = Model(HashIndex(told["token"].to_numpy(np.int64).view(np.uint64)), told[f"s{f}"].to_numpy(float), drift, 1.0, 1.0, np.zeros(3))
    model = models[0]
    found = sample.select("label", _cross_fitted(models, spark).alias("s")).select("label", "s.*").toPandas()  # a few numbers per training text
    if not len(found):
        model.weights = np.array([-30.0, 0.0, 0.0])
        return model, 0.0
    clean = found[(found["label"] == 0) & (found["n_words"] > 0)]
    if len(clean):
        model.decay = _decay(np.stack(clean["powers"].to_list()).sum(axis=0) / clean["n_words"].sum())
        best = clean["scores"].map(lambda s: max(s, default=0.0)).to_numpy(float)
        model.size_factor = float(np.exp(np.mean(model.decay * best - np.log(clean["n_words"].to_numpy(float))) - EULER))
    x = np.array([model.features(w, [(0, 0, s) for s in ss]) for w, ss in zip(found["n_words"], found["scores"], strict=True)])
    y = found["label"].to_numpy(float)
    model.weights = logistic(x, y)
    p = np.clip(1 / (1 + np.exp(-np.clip(x @ model.weights, -30, 30))), 1e-12, 1 - 1e-12)
    return model, float(-(y * np.log(p) + (1 - y) * np.log(1 - p)).mean())


def _cross_fitted(models: dict[int, Model], spark) -> Column:
    """Words, segment scores and summed powers of word scores of each training text, by the model without its fold."""
    shared = spark.sparkContext.broadcast(models)

    def run(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
        for texts, folds in batches:
            data, offsets = utf8_view(texts)
            fold = folds.to_numpy()
            out: list[dict] = [{} for _ in range(len(fold))]
            for f in np.unique(fold).tolist():
                at = np.flatnonzero(fold == f)
                own, own_offsets = utf8_view(texts.take(pa.array(at)))
                for a, b in blocks(own_offsets):
                    values: list[np.ndarray] = []
                    words, segments = shared.value[f].segments(own[own_offsets[a] : own_offsets[b]], own_offsets[a : b + 1] - own_offsets[a], values)
                    ends = np.concatenate([[0], np.cumsum(words)])
                    powers = np.stack([row_sums(np.exp(np.minimum(d * values[0], 300.0)), ends) for d in DECAYS], axis=1)
                    for i in range(b - a):
                        out[at[a + i]] = {"n_words": int(words[i]), "scores": [s for _, _, s in segments[i]], "powers": powers[i].tolist()}
            yield pa.array(out, pa.struct([("n_words", pa.int64()), ("scores", pa.list_(pa.float64())), ("powers", pa.list_(pa.float64()))]))

    run.__annotations__ = {"batches": Iterator[tuple[pa.Array, pa.Array]], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, "n_words long, scores array<double>, powers array<double>").asNondeterministic()(F.col("text"), F.col("fold"))


def score_array(model: Model, texts: pa.Array) -> pa.Array:
    """Score, words and significant segments (in words) of each whole text; null is empty."""
    data, offsets = utf8_view(texts)
    out = []
    for a, b in blocks(offsets):
        words, segments = model.segments(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
        scores = model.score([model.features(n, s) for n, s in zip(words.tolist(), segments, strict=True)])
        for n, row, score in zip(words.tolist(), segments, scores.tolist(), strict=True):
            rated = [(s, e, v, model.expected(v, n)) for s, e, v in row]
            out.append({"score": score, "n_words": n, "segments": [{"start": s, "stop": e, "score": v, "expected": x} for s, e, v, x in rated if x <= SIGNIFICANT]})
    return pa.array(out, RESULT)


def toxicity(text: Column, model: Model, spark) -> Column:
    """Struct ``score, n_words, segments`` of each whole text."""
    shared = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            yield score_array(shared.value, texts)

    run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, RESULT_DDL).asNondeterministic()(text.cast("string"))


def keep_clean(docs: DataFrame, model: Model, threshold: float = 0.5, text_col: str = "text") -> DataFrame:
    """Documents that score below ``threshold``, with their columns as they were, whatever their names.

    Null and empty texts score as texts without words, repeated rows alike; an empty table stays empty.
    """
    found = free_name(docs, "__toxicity")
    scored = docs.withColumn(found, toxicity(F.col(text_col), model, docs.sparkSession))
    return scored.where(F.col(found)["score"] < threshold).select(*quoted(docs))
