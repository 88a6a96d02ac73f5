"""Language identification by prediction by partial matching (PPM, escape method C).

Each language has a byte context tree of orders 0 to ``ORDER`` with frozen
counts. A byte seen after its longest known context costs -log2 c/(n+t) bits,
one not seen costs the escape t/(n+t) and is looked up one order lower, down to
a uniform byte. The language with the shortest exact code for the whole text
wins. The trees of all languages share one table per order, so a byte of text
costs one lookup however many languages there are, and misses a few more.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.llm.bytetext import LOWER, HashIndex, blocks, row_sums, utf8_view
from modelsort.llm.samples import least_hashes

ORDER = 4
#: Training texts per language, those of least hash: the documented bound of the sample.
TRAIN_TEXTS = 1_000
UNDETERMINED = "und"
PAD = 10

_ASCII_LETTER = np.zeros(256, bool)
_ASCII_LETTER[65:91] = _ASCII_LETTER[97:123] = True


def fold(data: np.ndarray) -> np.ndarray:
    """Lower case of ASCII and of the Latin-1 letters that UTF-8 writes as C3 80 to C3 9E."""
    out = LOWER[data]
    if len(out) > 1:
        upper = np.flatnonzero((data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E) & (data[1:] != 0x97)) + 1
        out[upper] += 0x20
    return out


def grams(data: np.ndarray, offsets: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """For each byte of each text, the byte and its ``order`` predecessors in one number, newest lowest.

    Texts are preceded by line ends, so the first bytes have contexts too.
    """
    rows, counts = len(offsets) - 1, np.diff(offsets)
    padded = np.full(len(data) + order * rows, PAD, np.uint8)
    at = np.arange(len(data)) + order * (np.repeat(np.arange(rows), counts) + 1)
    padded[at] = data
    code = np.zeros(len(data), np.uint64)
    for k in range(order + 1):
        code |= padded[at - k].astype(np.uint64) << np.uint64(8 * k)
    return code, at


def _low(code: np.ndarray, count: int) -> np.ndarray:
    """The newest ``count`` bytes of each gram; their number is put above them to keep lengths apart."""
    return code & np.uint64((1 << (8 * count)) - 1)


@dataclass
class Trees:
    """Frozen statistics: per order, log2 probabilities of grams and escapes of contexts, a column a language."""

    languages: list[str]
    order: int
    grams: list[HashIndex]
    costs: list[np.ndarray]
    contexts: list[HashIndex]
    escapes: list[np.ndarray]

    @classmethod
    def freeze(cls, counts: dict[str, tuple[np.ndarray, np.ndarray]], order: int = ORDER) -> Trees:
        """Trees from each language's distinct longest grams and their counts."""
        languages = sorted(counts)
        tables: list[tuple] = []
        for k in range(order + 1):
            known, contexts, per = [], [], []
            for name in languages:
                code, number = counts[name]
                gram, back = np.unique(_low(code, k + 1), return_inverse=True)
                n = np.bincount(back, weights=number, minlength=len(gram))
                context, ctx_back = np.unique(gram >> np.uint64(8), return_inverse=True)
                total = np.bincount(ctx_back, weights=n, minlength=len(context))
                kinds = np.bincount(ctx_back, minlength=len(context))
                known.append(gram)
                contexts.append(context)
                per.append((gram, n, ctx_back, total, kinds))
            all_grams, all_contexts = np.unique(np.concatenate(known)), np.unique(np.concatenate(contexts))
            escape = np.zeros((len(all_contexts), len(languages)), np.float32)
            cost = np.full((len(all_grams), len(languages)), np.nan, np.float32)
            for j, (gram, n, ctx_back, total, kinds) in enumerate(per):
                escape[np.searchsorted(all_contexts, contexts[j]), j] = -np.log2(kinds / (total + kinds))
                cost[np.searchsorted(all_grams, gram), j] = -np.log2(n / (total + kinds)[ctx_back])
            lower = tables[-1][1][np.searchsorted(tables[-1][0], _low(all_grams, k))] if k else np.full(cost.shape, 8.0, np.float32)
            missing = np.isnan(cost)
            cost[missing] = (escape[np.searchsorted(all_contexts, all_grams >> np.uint64(8))] + lower)[missing]
            tables.append((all_grams, cost, all_contexts, escape))
        return cls(languages, order, [HashIndex(t[0]) for t in tables], [t[1] for t in tables], [HashIndex(t[2]) for t in tables], [t[3] for t in tables])

    def code_lengths(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Bits that each language's tree needs for each whole text."""
        code, _ = grams(fold(data), offsets, self.order)
        top = self.grams[self.order].find(code)
        bits = np.zeros((len(offsets) - 1, len(self.languages)))
        known = np.maximum(top, 0)
        for j in range(len(self.languages)):
            cost = self.costs[self.order][:, j][known] if len(self.costs[self.order]) else np.zeros(len(code), np.float32)
            cost[top < 0] = 0
            bits[:, j] = row_sums(cost.astype(np.float64), offsets)
        left = np.flatnonzero(top < 0)
        if len(left):
            extra = np.zeros((len(left), len(self.languages)), np.float64)
            going = np.arange(len(left))
            for k in range(self.order, -1, -1):
                context = self.contexts[k].find(_low(code[left[going]], k + 1) >> np.uint64(8))
                has = context >= 0
                extra[going[has]] += self.escapes[k][context[has]]
                if k == 0:
                    extra[going] += 8.0
                    break
                found = self.grams[k - 1].find(_low(code[left[going]], k))
                hit = found >= 0
                extra[going[hit]] += self.costs[k - 1][found[hit]]
                going = going[~hit]
                if not len(going):
                    break
            row = np.searchsorted(offsets, left, side="right") - 1
            for j in range(len(self.languages)):
                bits[:, j] += np.bincount(row, weights=extra[:, j], minlength=len(offsets) - 1)
        return bits


def _has_letter(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    found = row_sums(_ASCII_LETTER[data], offsets) > 0
    for i in np.flatnonzero(~found & (row_sums(data >= 0x80, offsets) > 0)).tolist():
        found[i] = any(c.isalpha() for c in bytes(data[offsets[i] : offsets[i + 1]]).decode("utf-8", "ignore"))
    return found


RESULT = pa.struct([("lang", pa.string()), ("score", pa.float64()), ("bits", pa.list_(pa.float64()))])
RESULT_DDL = "lang string, score double, bits array<double>"


def predict_array(trees: Trees, texts: pa.Array) -> pa.Array:
    """Language, its posterior under equal priors, and the code lengths in bits."""
    data, offsets = utf8_view(texts)
    names, scores, lengths = [], [], []
    for a, b in blocks(offsets):
        part, off = data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        letters = _has_letter(part, off)
        if not trees.languages:
            names += [UNDETERMINED] * (b - a)
            scores += [0.0] * (b - a)
            lengths += [[]] * (b - a)
            continue
        bits = trees.code_lengths(part, off)
        best = bits.argmin(axis=1)
        posterior = 1.0 / np.exp2(np.maximum(bits.min(axis=1, keepdims=True) - bits, -1000.0)).sum(axis=1)
        names += [trees.languages[j] if ok else UNDETERMINED for j, ok in zip(best.tolist(), letters.tolist(), strict=True)]
        scores += np.where(letters, posterior, 0.0).tolist()
        lengths += bits.tolist()
    return pa.StructArray.from_arrays([pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(lengths, pa.list_(pa.float64()))], names=["lang", "score", "bits"])


def train(docs: DataFrame, lang_col: str = "lang", text_col: str = "text", order: int = ORDER, texts: int = TRAIN_TEXTS) -> Trees:
    """Trees of every language of ``docs``, from at most ``texts`` distinct texts each.

    The sample is the texts of least hash, so it doesn't depend on partitions.
    Rows without language or text teach nothing; no rows at all give trees
    without languages, which predict ``und``.
    """
    rows = docs.select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("text")).where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.col("text") != ""))
    sample = least_hashes(rows.withColumn("h", F.xxhash64("text")), "h", texts, "lang")

    def count(table: pa.Table) -> pa.Table:
        seen: list[tuple[np.ndarray, np.ndarray]] = []
        data, offsets = utf8_view(table.column("text"))
        for a, b in blocks(offsets):
            code, _ = grams(fold(data[offsets[a] : offsets[b]]), offsets[a : b + 1] - offsets[a], order)
            seen.append(np.unique(code, return_counts=True))
        code, back = np.unique(np.concatenate([s[0] for s in seen]), return_inverse=True)
        number = np.bincount(back, weights=np.concatenate([s[1] for s in seen])).astype(np.int64)
        return pa.table({"lang": [table.column("lang")[0].as_py()], "grams": [code.tobytes()], "counts": [number.tobytes()]}, schema=pa.schema([("lang", pa.string()), ("grams", pa.binary()), ("counts", pa.binary())]))

    learned = sample.groupBy("lang").applyInArrow(count, "lang string, grams binary, counts binary").collect()  # a row a language, bounded by the sample
    return Trees.freeze({r["lang"]: (np.frombuffer(r["grams"], np.uint64), np.frombuffer(r["counts"], np.int64)) for r in learned}, order) if learned else Trees([], order, [], [], [], [])


def predict(text: Column, trees: Trees, spark) -> Column:
    """Struct ``lang, score, bits``: ``und`` and score 0 where the text is null or has no letter."""
    shared = spark.sparkContext.broadcast(trees)

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            yield predict_array(shared.value, texts)

    run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, RESULT_DDL).asNondeterministic()(text.cast("string"))
