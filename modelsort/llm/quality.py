"""Quality by attention-based multiple-instance learning.

A text is a bag of passages of ``PASSAGE`` words; only the bag has a label. Each
passage is encoded by a learned layer over the mean of its words' and character
trigrams' hashed indicators, which is the mean of learned embeddings of hashed words
and trigrams, and over its byte classes and the repetition of its words. Gated attention gives each passage its weight, and
the weighted sum of encodings gives the document's probability. Encoder, gates
and classifier are trained together on the document labels.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.llm.bytetext import LOWER, NOT_SPACE, blocks, utf8_view, word_bounds, word_hashes
from modelsort.llm.samples import free_name, labelled_sample, quoted

PASSAGE = 128
#: Labelled documents that the model is fitted on at most.
TRAIN_DOCS = 8_000
#: Hash buckets of words and of character trigrams, each with an embedding of its own.
WORD_BUCKETS, GRAM_BUCKETS = 256, 256
THRESHOLD = 0.3
EPOCHS = 12
DECAY = 1e-3
HIDDEN, GATES = 16, 8

#: Byte classes, each as the bytes that belong to it; what is left forms the last class.
CLASSES = [b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b" ", b"\n", b".", b",", b"!", b"?", b"|", b"#$%&*@^~", b"-_=+", b":;/\\", b"\"'`", b"()[]{}<>", bytes(range(128, 256))]
_CLASS = np.full(256, len(CLASSES), np.int64)
for _k, _members in enumerate(CLASSES):
    _CLASS[np.frombuffer(_members, np.uint8)] = _k
N_CLASSES = len(CLASSES) + 1
N_SHAPE = N_CLASSES + 5
N_FEATURES = N_SHAPE + WORD_BUCKETS + GRAM_BUCKETS


def describe(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Features of all passages of a block of texts, and the offsets of texts among them.

    A text without words is one passage; every byte of a text belongs to its own passages.
    """
    starts, ends, bounds = word_bounds(data, offsets, NOT_SPACE)
    rows = len(offsets) - 1
    counts = np.diff(bounds)
    passages = np.maximum(1, -(-counts // PASSAGE))
    first = np.concatenate([[0], np.cumsum(passages)])
    row = np.repeat(np.arange(rows), counts)
    passage = first[row] + (np.arange(len(starts)) - bounds[row]) // PASSAGE
    total = int(first[-1])
    words = np.bincount(passage, minlength=total).astype(float)
    x = np.zeros((total, N_FEATURES))
    # A byte belongs to the passage of the last word of its text that starts at or before it; leading blanks to the first passage.
    begin = np.empty(total, np.int64)
    heads = np.flatnonzero(np.append(True, passage[1:] != passage[:-1])) if len(starts) else np.zeros(0, np.int64)
    begin[passage[heads]] = starts[heads]
    begin[first[:-1]] = offsets[:-1]
    of_byte = np.repeat(np.arange(total), np.diff(np.append(begin, len(data))))
    x[:, :N_CLASSES] = np.bincount(of_byte * N_CLASSES + _CLASS[data], minlength=total * N_CLASSES).reshape(total, N_CLASSES)
    size = np.maximum(x[:, :N_CLASSES].sum(axis=1), 1.0)
    x[:, :N_CLASSES] = np.sqrt(x[:, :N_CLASSES] / size[:, None])
    x[:, N_SHAPE + WORD_BUCKETS :] = _shares(of_byte, _trigrams(data, offsets) >> np.uint32(32 - 8), total, GRAM_BUCKETS)
    if not len(starts):
        return x, first
    lengths = (ends - starts).astype(float)
    some = np.maximum(words, 1.0)
    x[:, N_CLASSES] = np.log1p(words)
    x[:, N_CLASSES + 1] = np.bincount(passage, weights=lengths, minlength=total) / some / 10
    x[:, N_CLASSES + 2] = np.bincount(passage, weights=lengths == 1, minlength=total) / some
    hashes = word_hashes(LOWER[data], starts, ends)
    x[:, N_SHAPE : N_SHAPE + WORD_BUCKETS] = _shares(passage, hashes >> np.uint64(64 - 8), total, WORD_BUCKETS)
    pairs = hashes[:-1] * np.uint64(3) + hashes[1:]
    x[:, N_CLASSES + 3] = _distinct(passage, hashes, total) / some
    same = passage[1:] == passage[:-1]
    x[:, N_CLASSES + 4] = _distinct(passage[1:][same], pairs[same], total) / np.maximum(words - 1, 1.0)
    return x, first


def _trigrams(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Hash of each byte and its two predecessors within its text, in lower case."""
    low = LOWER[data].astype(np.uint32)
    one, two = np.zeros_like(low), np.zeros_like(low)
    one[1:], two[2:] = low[:-1], low[:-2]
    begins = offsets[:-1][offsets[:-1] < len(low)]
    one[begins] = two[begins] = 0
    second = begins + 1
    two[second[second < len(low)]] = 0
    code = low | (one << np.uint32(8)) | (two << np.uint32(16))
    with np.errstate(over="ignore"):
        code *= np.uint32(0x9E3779B1)
        return (code ^ (code >> np.uint32(15))) * np.uint32(0x85EBCA77)


def _shares(passage: np.ndarray, bucket: np.ndarray, total: int, buckets: int) -> np.ndarray:
    """Root of the share of each passage's items that fall to each bucket."""
    counts = np.bincount(passage * buckets + bucket.astype(np.int64), minlength=total * buckets).reshape(total, buckets)
    return np.sqrt(counts / np.maximum(counts.sum(axis=1), 1)[:, None])


def _distinct(passage: np.ndarray, hashes: np.ndarray, total: int) -> np.ndarray:
    """Distinct hashes of each passage (by their upper bits)."""
    bits = np.uint64(max(1, int(total).bit_length()))
    keys = np.sort((passage.astype(np.uint64) << (np.uint64(64) - bits)) | (hashes >> bits))
    fresh = np.append(True, keys[1:] != keys[:-1]) if len(keys) else np.zeros(0, bool)
    return np.bincount((keys[fresh] >> (np.uint64(64) - bits)).astype(np.int64), minlength=total)


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


@dataclass
class Network:
    """Encoder, gated attention and classifier over standardised passage features."""

    mean: np.ndarray
    scale: np.ndarray
    weights: dict[str, np.ndarray]
    constant: float | None = None

    @classmethod
    def fresh(cls, x: np.ndarray, rng: np.random.Generator) -> Network:
        near = lambda a, b: rng.normal(0, 1 / np.sqrt(a), (a, b))
        w = {"enc": near(x.shape[1], HIDDEN), "enc0": np.zeros(HIDDEN), "val": near(HIDDEN, GATES), "gate": near(HIDDEN, GATES), "att": near(GATES, 1)[:, 0], "out": near(HIDDEN, 1)[:, 0], "out0": np.zeros(1)}
        return cls(x.mean(axis=0), x.std(axis=0) + 1e-3, w)

    def forward(self, x: np.ndarray, first: np.ndarray) -> dict[str, np.ndarray]:
        w, bag = self.weights, np.repeat(np.arange(len(first) - 1), np.diff(first))
        v = np.clip((x - self.mean) / self.scale, -8, 8)
        h = np.tanh(v @ w["enc"] + w["enc0"])
        t, g = np.tanh(h @ w["val"]), _sigmoid(h @ w["gate"])
        e = (t * g) @ w["att"]
        e = np.exp(e - np.maximum.reduceat(e, first[:-1])[bag])
        a = e / np.add.reduceat(e, first[:-1])[bag]
        z = np.add.reduceat(a[:, None] * h, first[:-1], axis=0)
        return {"v": v, "h": h, "t": t, "g": g, "a": a, "z": z, "bag": bag, "p": _sigmoid(z @ w["out"] + w["out0"][0])}

    def gradients(self, f: dict[str, np.ndarray], first: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        w, bag, n = self.weights, f["bag"], len(y)
        d = (f["p"] - y) / n
        dz = d[:, None] * w["out"]
        da = (dz[bag] * f["h"]).sum(axis=1)
        de = f["a"] * (da - np.add.reduceat(f["a"] * da, first[:-1])[bag])
        dt, dg = de[:, None] * w["att"] * f["g"] * (1 - f["t"] ** 2), de[:, None] * w["att"] * f["t"] * f["g"] * (1 - f["g"])
        dh = (f["a"][:, None] * dz[bag] + dt @ w["val"].T + dg @ w["gate"].T) * (1 - f["h"] ** 2)
        return {"enc": f["v"].T @ dh, "enc0": dh.sum(axis=0), "val": f["h"].T @ dt, "gate": f["h"].T @ dg, "att": (f["t"] * f["g"]).T @ de, "out": f["z"].T @ d, "out0": np.array([d.sum()])}

    def predict(self, x: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Probability of each text and the attention of each passage."""
        if self.constant is not None:
            return np.full(len(first) - 1, self.constant), np.repeat(1 / np.diff(first), np.diff(first))
        f = self.forward(x, first)
        return f["p"], f["a"]


def fit(x: np.ndarray, first: np.ndarray, y: np.ndarray, epochs: int = EPOCHS, batch: int = 64, rate: float = 0.01, seed: int = 7) -> Network:
    """Train by Adam over shuffled batches of bags."""
    if not len(y) or y.min() == y.max():
        return Network(np.zeros(N_FEATURES), np.ones(N_FEATURES), {}, float(y[0]) if len(y) else 0.0)
    rng = np.random.default_rng(seed)
    net = Network.fresh(x, rng)
    slow = {k: np.zeros_like(v) for k, v in net.weights.items()}
    square = {k: np.zeros_like(v) for k, v in net.weights.items()}
    step, steps = 0, epochs * -(-len(y) // batch)
    for _ in range(epochs):
        order = rng.permutation(len(y))
        for a in range(0, len(y), batch):
            bags = order[a : a + batch]
            sizes = np.diff(first)[bags]
            at = np.concatenate([[0], np.cumsum(sizes)])
            rows = np.repeat(first[:-1][bags] - at[:-1], sizes) + np.arange(at[-1])
            step += 1
            for k, g in net.gradients(net.forward(x[rows], at), at, y[bags]).items():
                g = g + DECAY * net.weights[k]
                slow[k] = 0.9 * slow[k] + 0.1 * g
                square[k] = 0.99 * square[k] + 0.01 * g * g
                now = rate * (1 - step / (steps + 1))
                net.weights[k] -= now * slow[k] / (1 - 0.9**step) / (np.sqrt(square[k] / (1 - 0.99**step)) + 1e-8)
    return net


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", n: int = TRAIN_DOCS, text_col: str = "text") -> Network:
    """Network of ``label`` from at most ``n`` labelled documents outside fold 0.

    With examples of one class only, or none, every text scores 1 or 0. Null texts
    are empty ones, repeated rows teach again; columns beside id and text are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8_view(batch.column("text"))
            for a, b in blocks(offsets):
                x, first = describe(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                parts = [x[s:e].astype(np.float16).tobytes() for s, e in zip(first[:-1], first[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("label")[a:b].cast(pa.int32()), pa.array(parts, pa.binary())], names=["label", "features"])

    sample = labelled_sample(docs, labels, label, n, text_col=text_col).select("text", "label")
    rows = sample.mapInArrow(run, "label int, features binary").collect()  # bounded by the sample
    rows.sort(key=lambda r: (r["features"], r["label"]))
    bags = [np.frombuffer(r["features"], np.float16).reshape(-1, N_FEATURES) for r in rows]
    first = np.concatenate([[0], np.cumsum([len(b) for b in bags])]).astype(np.int64)
    return fit(np.concatenate(bags).astype(np.float32) if bags else np.zeros((0, N_FEATURES)), first, np.array([r["label"] for r in rows], float))


RESULT_DDL = "score double, n_passages long, weightiest long, weight double"


def score_array(net: Network, texts: pa.Array) -> pa.Array:
    """Score of each whole text, its passages, and which weighs most; null is empty."""
    data, offsets = utf8_view(texts)
    scores, counts, tops, weights = [], [], [], []
    for a, b in blocks(offsets):
        x, first = describe(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
        p, attention = net.predict(x, first)
        best = np.maximum.reduceat(attention, first[:-1])
        at = np.flatnonzero(attention == np.repeat(best, np.diff(first)))
        scores.append(p)
        counts.append(np.diff(first))
        tops.append(at[np.searchsorted(at, first[:-1])] - first[:-1])
        weights.append(best)
    join = lambda parts, kind: pa.array(np.concatenate(parts) if parts else [], kind)
    return pa.StructArray.from_arrays([join(scores, pa.float64()), join(counts, pa.int64()), join(tops, pa.int64()), join(weights, pa.float64())], names=["score", "n_passages", "weightiest", "weight"])


def quality(text: Column, net: Network, spark) -> Column:
    """Struct ``score, n_passages, weightiest, weight`` of each whole text."""
    shared = spark.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            yield score_array(shared.value, texts)

    run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, RESULT_DDL).asNondeterministic()(text.cast("string"))


def keep_good(docs: DataFrame, net: Network, threshold: float = THRESHOLD, text_col: str = "text") -> DataFrame:
    """Documents that score ``threshold`` or more, with their columns as they were, whatever their names.

    Null and empty texts score as one passage without words, repeated rows alike; an empty table stays empty.
    """
    found = free_name(docs, "__quality")
    scored = docs.withColumn(found, quality(F.col(text_col), net, docs.sparkSession))
    return scored.where(F.col(found)["score"] >= threshold).select(*quoted(docs))
