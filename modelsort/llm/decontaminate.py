"""Benchmark decontamination with suffix arrays over the training texts.

Each block of training text gets the suffix array of all its words, in the
order of their next ``DEPTH`` words, by prefix doubling. Every suffix of every
benchmark item is binary-searched in it, all at once and one word deeper at a
time: an interval of training suffixes shares the first k words, and the next
word is looked up within it. Where a search ends is the longest verbatim match;
intervals that survive to the array's depth are followed word by word. A
window's hits are the interval that its suffix has at the window's length, and a
text's longest match is that of its best suffix.

Words are compared as numbers, which the hashes of the benchmark's words give;
the bytes of every word that a result rests on are compared too.

The benchmark is the stated query set. It is sent to the tasks in blocks of
bounded size; more than one block means one more pass per block.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.llm.bytetext import LOWER, HashIndex, blocks, row_sums, utf8_view, word_bounds, word_hashes
from modelsort.llm.samples import free_name, quoted
from modelsort.plans.durable import materialize

WINDOW = 13
#: A document is contaminated when hit words are at least one in so many.
HIT_ONE_IN = 20
#: Benchmark characters that one pass sends to every task.
PASS_CHARS = 4_000_000
#: Bytes of training text that one suffix array holds (more if one text does), and words that its order compares.
TEXT_BLOCK = 4 << 20
DEPTH = 16

MATCH = pa.struct([
    ("n_words", pa.int64()),
    ("n_hit", pa.int64()),
    ("items", pa.list_(pa.string())),
    ("spans", pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))),
    ("longest", pa.struct([("item_id", pa.string()), ("words", pa.int64()), ("doc_word", pa.int64()), ("item_word", pa.int64())])),
])
MATCH_DDL = "n_words long, n_hit long, items array<string>, spans array<struct<start:long,stop:long>>, longest struct<item_id:string,words:long,doc_word:long,item_word:long>"


def _gather(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Bytes of some words, one after another."""
    ends = np.cumsum(lengths)
    return data[np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - (ends - lengths), lengths)]


def suffix_array(ids: np.ndarray, n: int, most: int) -> np.ndarray:
    """Positions 0 to n - 1 in the order of the next ``DEPTH`` numbers from each.

    ``ids`` are numbers from 0 to ``most``, with zeros from n on. The first keys
    hold as many words as fit 62 bits; each round doubles the words compared.
    """
    bits = max(1, int(most).bit_length())
    depth = max(1, min(DEPTH, 62 // bits))
    key = np.zeros(n, np.int64)
    for k in range(depth):
        key = (key << bits) | ids[k : n + k]
    while True:
        order = np.argsort(key, kind="stable")
        if depth >= DEPTH:
            return order
        ranked = key[order]
        rank = np.empty(n, np.int64)
        rank[order] = np.cumsum(np.append(True, ranked[1:] != ranked[:-1])) if n else rank
        after = np.zeros(n, np.int64)
        after[: max(n - depth, 0)] = rank[depth:]
        key, depth = rank * np.int64(n + 1) + after, 2 * depth


def _bisect(array: np.ndarray, ids: np.ndarray, depth: int, low: np.ndarray, high: np.ndarray, word: np.ndarray, right: bool) -> np.ndarray:
    """In each interval of the array, the first place whose word at ``depth`` is not less than (or above) the one wanted."""
    low, high = low.copy(), high.copy()
    while (open_ := np.flatnonzero(low < high)).size:
        middle = (low[open_] + high[open_]) >> 1
        found = ids[array[middle] + depth]
        less = found <= word[open_] if right else found < word[open_]
        low[open_[less]] = middle[less] + 1
        high[open_[~less]] = middle[~less]
    return low


@dataclass
class BenchmarkIndex:
    """Benchmark words as numbers from 1, their bytes, and the items they belong to."""

    names: list[str]  # of each item text
    labels: list[str]  # the distinct names
    label: np.ndarray  # of each item text among the labels
    vocabulary: HashIndex
    word_bytes: np.ndarray  # of the distinct words, one after another
    word_starts: np.ndarray
    words: np.ndarray  # numbers of all items' words, then zeros
    bounds: np.ndarray  # offsets of items in ``words``
    item: np.ndarray  # of each word
    window: np.ndarray  # words of the window that starts at each word, 0 where none does

    @classmethod
    def build(cls, names: list[str], texts: list[str | None], window: int = WINDOW) -> BenchmarkIndex:
        data, offsets = utf8_view(pa.array(texts, pa.string()))
        low = LOWER[data]
        starts, ends, bounds = word_bounds(low, offsets)
        known, first, ids = np.unique(word_hashes(low, starts, ends), return_index=True, return_inverse=True)
        lengths = (ends - starts)[first]
        held = _gather(low, starts[first], lengths)
        word_starts = np.cumsum(np.append(0, lengths))
        # Different words with one hash would pass for one another; none are known, and none may go unnoticed.
        if not (np.array_equal(ends - starts, lengths[ids]) and np.array_equal(_gather(low, starts, ends - starts), _gather(held, word_starts[ids], lengths[ids]))):
            raise ValueError("two benchmark words share a hash")
        sizes = np.diff(bounds)
        item = np.repeat(np.arange(len(names)), sizes)
        size = np.minimum(window, sizes)[item]
        windows = np.where(np.arange(len(item)) + size <= bounds[1:][item], size, 0)
        labels = sorted(set(names))
        of = {name: i for i, name in enumerate(labels)}
        words = np.append(ids + 1, np.zeros(1, np.int64)).astype(np.int64)
        return cls(names, labels, np.array([of[n] for n in names], np.int64), HashIndex(known), held, word_starts, words, bounds, item, windows)

    def _numbers(self, low: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Number of each word, 0 for those that the benchmark doesn't hold, byte for byte."""
        ids = self.vocabulary.find(word_hashes(low, starts, ends)).astype(np.int64) + 1
        at = np.flatnonzero(ids)
        lengths = (ends - starts)[at]
        wanted = np.diff(self.word_starts)[ids[at] - 1] if len(at) else lengths
        wrong = lengths != wanted
        same = at[~wrong]
        size = lengths[~wrong]
        different = _gather(low, starts[same], size) != _gather(self.word_bytes, self.word_starts[ids[same] - 1], size)
        if different.any():
            ids[same[np.unique(np.searchsorted(np.cumsum(size), np.flatnonzero(different), side="right"))]] = 0
        ids[at[wrong]] = 0
        return ids

    def search(self, ids: np.ndarray, array: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
        """For each number of words, the benchmark suffixes that some training suffix shares them with, and its interval."""
        suffix = np.arange(len(self.item))
        low, high = np.zeros(len(suffix), np.int64), np.full(len(suffix), len(array))
        end = self.bounds[1:][self.item]
        for depth in range(DEPTH):
            going = np.flatnonzero((suffix + depth < end[suffix]) & (low < high))
            suffix, low, high = suffix[going], low[going], high[going]
            word = self.words[suffix + depth]
            low, high = _bisect(array, ids, depth, low, high, word, False), _bisect(array, ids, depth, low, high, word, True)
            alive = low < high
            suffix, low, high = suffix[alive], low[alive], high[alive]
            if not len(suffix):
                return
            yield depth + 1, suffix, low, high

    def _follow(self, ids: np.ndarray, where: np.ndarray, suffix: np.ndarray) -> np.ndarray:
        """Words that each pair of a training and a benchmark position goes on sharing after ``DEPTH``."""
        length = np.full(len(where), DEPTH)
        end = self.bounds[1:][self.item[suffix]]
        going = np.flatnonzero(suffix + DEPTH < end)
        while len(going):
            same = ids[where[going] + length[going]] == self.words[suffix[going] + length[going]]
            going = going[same]
            length[going] += 1
            going = going[suffix[going] + length[going] < end[going]]
        return length

    def match(self, data: np.ndarray, offsets: np.ndarray) -> pa.StructArray:
        """Hits of each text of a block."""
        low_case = LOWER[data]
        starts, ends, bounds = word_bounds(low_case, offsets)
        n, rows, counts = len(starts), len(offsets) - 1, np.diff(bounds)
        plain = self._numbers(low_case, starts, ends)
        # A text's end is a number that no benchmark word has; so is a word of other texts.
        ids = np.zeros(n + rows + DEPTH + 1, np.int64)
        row = np.repeat(np.arange(rows), counts)
        at = np.arange(n) + row
        ids[at] = plain
        total = n + rows
        array = suffix_array(ids, total, int(self.words.max(initial=0))) if plain.any() else np.zeros(0, np.int64)
        best, place = np.zeros(total, np.int64), np.full(total, -1)  # longest match of each training suffix, and with what
        found_where, found_suffix = [], []
        for depth, suffix, low, high in self.search(ids, array) if len(array) else ():
            by = np.lexsort((suffix, low))
            first = by[np.append(True, low[by][1:] != low[by][:-1])]  # intervals of one depth are equal or disjoint
            sizes = (high - low)[first]
            spot = array[np.repeat(low[first] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())]
            best[spot], place[spot] = depth, np.repeat(suffix[first], sizes)
            whole = np.flatnonzero(self.window[suffix] == depth)
            if len(whole):
                sizes = (high - low)[whole]
                found_where.append(array[np.repeat(low[whole] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())])
                found_suffix.append(np.repeat(suffix[whole], sizes))
            if depth == DEPTH:
                sizes = high - low
                spot = array[np.repeat(low - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())]
                with_ = np.repeat(suffix, sizes)
                length = self._follow(ids, spot, with_)
                by = np.lexsort((with_, -length, spot))
                top = by[np.append(True, spot[by][1:] != spot[by][:-1])]
                best[spot[top]], place[spot[top]] = length[top], with_[top]
        where = np.concatenate(found_where) if found_where else np.zeros(0, np.int64)
        which = np.concatenate(found_suffix) if found_suffix else np.zeros(0, np.int64)
        return self._collected(bounds, row, at, total, best, place, where, which)

    def _collected(self, bounds: np.ndarray, row: np.ndarray, at: np.ndarray, total: int, best: np.ndarray, place: np.ndarray, where: np.ndarray, which: np.ndarray) -> pa.StructArray:
        """Columns of ``MATCH`` from longest matches by position and the windows found."""
        rows, counts = len(bounds) - 1, np.diff(bounds)
        edge = np.bincount(where, minlength=total + 1) - np.bincount(where + self.window[which], minlength=total + 1) if len(where) else np.zeros(total + 1, np.int64)
        hit = (np.cumsum(edge[:total]) > 0)[at]
        n_hit = row_sums(hit, bounds)
        first_of = np.searchsorted(at, where) if len(where) else where  # back to words without text ends
        text = row[first_of] if len(where) else where
        pair = np.unique(text * max(1, len(self.labels)) + self.label[self.item[which]]) if len(where) else where
        item_rows, item_labels = pair // max(1, len(self.labels)), pair % max(1, len(self.labels))
        names = pa.array(self.labels, pa.string()).take(pa.array(item_labels, pa.int64()))
        items = pa.ListArray.from_arrays(pa.array(np.searchsorted(item_rows, np.arange(rows + 1)), pa.int32()), names)
        begins = hit & np.append(True, ~hit[:-1] | (row[1:] != row[:-1])) if len(hit) else hit
        stops = hit & np.append(~hit[1:] | (row[1:] != row[:-1]), True) if len(hit) else hit
        a, b = np.flatnonzero(begins), np.flatnonzero(stops) + 1
        spans = pa.StructArray.from_arrays([pa.array(a - bounds[row[a]], pa.int64()), pa.array(b - bounds[row[a]], pa.int64())], names=["start", "stop"])
        span_lists = pa.ListArray.from_arrays(pa.array(np.searchsorted(a, bounds), pa.int32()), spans)
        length = best[at]
        top = np.zeros(rows, np.int64)
        full = counts > 0
        if full.any():
            top[full] = np.maximum.reduceat(length, bounds[:-1][full])
        lead = np.flatnonzero((length == top[row]) & (length > 0))
        first = lead[np.append(True, row[lead][1:] != row[lead][:-1])] if len(lead) else lead
        doc_word, suffix, item_id, item_word = (np.zeros(rows, np.int64) for _ in range(4))
        doc_word[row[first]], suffix[row[first]] = first - bounds[row[first]], place[at[first]]
        if len(first):
            item_id[row[first]] = self.item[suffix[row[first]]]
            item_word[row[first]] = suffix[row[first]] - self.bounds[item_id[row[first]]]
        none = top == 0
        texts = pa.array(self.names or [""], pa.string()).take(pa.array(item_id, pa.int64()))
        longest = pa.StructArray.from_arrays([texts, pa.array(top), pa.array(doc_word), pa.array(item_word)], names=["item_id", "words", "doc_word", "item_word"], mask=pa.array(none))
        return pa.StructArray.from_arrays([pa.array(counts.astype(np.int64)), pa.array(n_hit.astype(np.int64)), items, span_lists, longest], fields=list(MATCH))


def match_column(text: Column, index: BenchmarkIndex, spark) -> Column:
    """Struct of hits of each text against one block of the benchmark."""
    shared = spark.sparkContext.broadcast(index)

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            data, offsets = utf8_view(texts)
            found = [shared.value.match(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) for a, b in blocks(offsets, TEXT_BLOCK)]
            yield pa.concat_arrays(found) if found else pa.array([], MATCH)

    run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, MATCH_DDL).asNondeterministic()(text)


def _merge(found: Column, more: Column) -> Column:
    """Hits of one text against two blocks of the benchmark, taken together."""
    ordered = F.array_sort(F.concat(found["spans"], more["spans"]))
    merged = F.aggregate(
        ordered,
        F.array().cast("array<struct<start:long,stop:long>>"),
        lambda acc, s: F.when((F.size(acc) > 0) & (F.try_element_at(acc, F.lit(-1))["stop"] >= s["start"]), F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(F.struct(F.try_element_at(acc, F.lit(-1))["start"].alias("start"), F.greatest(F.try_element_at(acc, F.lit(-1))["stop"], s["stop"]).alias("stop"))))).otherwise(F.concat(acc, F.array(s))),
    )
    n_hit = F.aggregate(merged, F.lit(0).cast("long"), lambda acc, s: acc + s["stop"] - s["start"])
    longer = F.when(more["longest"].isNull() | (found["longest"]["words"] >= more["longest"]["words"]), found["longest"]).otherwise(more["longest"])
    return F.struct(found["n_words"].alias("n_words"), n_hit.alias("n_hit"), F.array_union(found["items"], more["items"]).alias("items"), merged.alias("spans"), longer.alias("longest"))


def with_matches(docs: DataFrame, benchmark: DataFrame, out: str = "match", text_col: str = "text", pass_chars: int = PASS_CHARS) -> DataFrame:
    """Add column ``out``: words, hit words, items, merged spans and the longest match of each text.

    Null and empty texts have no words. Benchmark rows with a null id or text
    are no items; rows that repeat an id are one item with all their windows.
    An empty benchmark hits nothing, an empty table stays empty. Columns and
    rows of ``docs`` are kept, whatever their names; ``out`` must not be among
    them. Repeated rows are each matched; very long texts are one block each.
    """
    spark = docs.sparkSession
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null and text is not null")
    chars = items.agg(F.sum(F.length("text"))).first()[0] or 0
    passes = max(1, -(-chars // pass_chars))
    part = F.pmod(F.xxhash64("item_id"), F.lit(passes))
    result = docs
    more = free_name(docs, "__more")
    for k in range(passes):
        rows = items.where(part == k).collect()  # about pass_chars characters of the query set
        index = BenchmarkIndex.build([r["item_id"] for r in rows], [r["text"] for r in rows])
        column = match_column(F.col(text_col).cast("string"), index, spark)
        if k == 0:
            result = result.withColumn(out, column)
        else:
            result = result.withColumn(more, column)
            result = materialize(result, "matches").withColumn(out, _merge(F.col(out), F.col(more))).drop(more)
    return result


def is_contaminated(match: Column, one_in: int = HIT_ONE_IN) -> Column:
    """The contract's rule: some word is hit and at least one word in ``one_in`` is."""
    return (match["n_hit"] > 0) & (one_in * match["n_hit"] >= match["n_words"])


def items_digest(items: Column) -> Column:
    """SHA-256 of the item ids, sorted as strings and joined with commas."""
    return F.sha2(F.array_join(F.array_sort(items), ","), 256)


def decontaminate(docs: DataFrame, benchmark: DataFrame, text_col: str = "text") -> DataFrame:
    """Documents that are not contaminated, with their columns as they were, whatever their names.

    Null and empty texts are clean, repeated rows are judged alike; an empty
    table or benchmark drops nothing.
    """
    found = free_name(docs, "__match")
    return with_matches(docs, benchmark, found, text_col).where(~is_contaminated(F.col(found))).select(*quoted(docs))


def brute_force(text: str | None, items: list[tuple[str, str]]) -> tuple[int, int, int, str, bool]:
    """The same counts by plain search, for tests."""
    words, hit, found = plain_words(text), set(), set()
    for name, item in items:
        own = plain_words(item)
        size = min(WINDOW, len(own))
        for p in range(len(own) - size + 1) if size else ():
            for q in range(len(words) - size + 1):
                if words[q : q + size] == own[p : p + size]:
                    hit |= set(range(q, q + size))
                    found.add(name)
    return len(words), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit) and HIT_ONE_IN * len(hit) >= len(words)


def brute_longest(text: str | None, items: list[tuple[str, str]]) -> int:
    """Words of the longest verbatim match by plain search, for tests."""
    words, best = plain_words(text), 0
    for _, item in items:
        own = plain_words(item)
        before = [0] * (len(own) + 1)
        for w in words:
            row = [0] * (len(own) + 1)
            for j, v in enumerate(own):
                if v == w:
                    row[j + 1] = before[j] + 1
            best, before = max(best, max(row)), row
    return best


def plain_words(text: str | None) -> list[str]:
    import re

    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
