"""Cuts within buckets that no numeric model can split: by the raw key, then by the ties.

A bucket of one numeric value may hold many raw keys (strings that share their
leading bytes, integers that a double rounds) or one key in many rows that ties
order. Cuts are rows of its sample, compared with the raw columns; a row's fine
bucket is its bucket plus the number of cuts at or before it. Cuts only decide
how rows are dealt, never their order, so any of them gives a right sort.
"""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from modelsort.functions.keys import KeySpec
from modelsort.functions.literals import int_array

BUCKET = "__bucket"
#: Sampled rows for each piece of a cut bucket.
PER_PIECE = 32
_FAR = (1 << 31) - 1


def _text(column: str, kind: T.DataType) -> Column:
    """A value as text that ``_literal`` reads back."""
    c = F.col(column)
    return F.hex(c.cast("binary")) if isinstance(kind, (T.StringType, T.BinaryType)) else c.cast("string")


def _literal(text: str | None, kind: T.DataType) -> str:
    name = kind.simpleString()
    if text is None:
        return f"CAST(NULL AS {name})"
    return f"CAST(X'{text}' AS {name})" if isinstance(kind, (T.StringType, T.BinaryType)) else f"CAST('{text}' AS {name})"


@dataclass
class Cuts:
    """Sorted cuts ``(bucket, texts of the order columns, beyond)``; ``beyond`` cuts lie after the rows equal to them."""

    key: KeySpec
    kinds: list[T.DataType]
    rows: list[tuple[int, tuple[str | None, ...], int]]
    per_bucket: dict[int, int] = field(default_factory=dict)

    def first(self, buckets: int) -> np.ndarray:
        """First fine bucket of each bucket."""
        extra = np.zeros(buckets, np.int64)
        for b, n in self.per_bucket.items():
            extra[b] = n
        return np.arange(buckets) + np.cumsum(extra) - extra

    def _reached(self, cut: Column) -> Column:
        """Whether a row lies at or beyond a cut in the order of the key."""
        out = cut["beyond"] == 0
        order = [(self.key.column, self.key.ascending, self.key.nulls_first), *((t, True, True) for t in self.key.ties)]
        for i, (name, ascending, nulls_first) in reversed(list(enumerate(order))):
            v, c = F.col(name), cut[f"k{i}"]
            null = c.isNull() & v.isNotNull() if nulls_first else v.isNull() & c.isNotNull()
            after = F.when(v.isNull() | c.isNull(), null).otherwise(v > c if ascending else v < c)
            out = after | (v.eqNullSafe(c) & out)
        return (F.col(BUCKET) > cut["bucket"]) | ((F.col(BUCKET) == cut["bucket"]) & out)

    def attach(self, df: DataFrame) -> DataFrame:
        """Turn the bucket column into the fine bucket, by a walk down a heap of the cuts in as many projections as it has levels."""
        if not self.rows:
            return df
        levels = int(np.ceil(np.log2(len(self.rows) + 1)))
        far = (_FAR, (None,) * len(self.kinds), 0)
        filled = [*self.rows, *[far] * (2**levels - 1 - len(self.rows))]
        heap = [filled[step // 2 - 1 + i * step] for level in range(levels) for step in [2 ** (levels - level)] for i in range(2**level)]
        cells = (", ".join([f"'bucket', {b}", *(f"'k{i}', {_literal(t, kind)}" for i, (t, kind) in enumerate(zip(texts, self.kinds, strict=True))), f"'beyond', {beyond}"]) for b, texts, beyond in heap)
        array = F.expr(f"array({', '.join(f'named_struct({c})' for c in cells)})")
        df = df.withColumn("__node", F.lit(1))
        for _ in range(levels):
            df = df.withColumn("__cut", F.element_at(array, F.col("__node"))).withColumn("__node", 2 * F.col("__node") + self._reached(F.col("__cut")).cast("int"))
        # A partition number has no sign bit, so nothing is added; but filters on the result stay above the walk,
        # whose expressions would otherwise be substituted into each other level by level.
        zero = F.shiftright(F.spark_partition_id(), 31)
        return df.withColumn(BUCKET, F.col(BUCKET) + F.col("__node") - F.lit(2**levels) + zero).drop("__node", "__cut")


def find_cuts(keys: DataFrame, key: KeySpec, rows: Mapping[int, int], target: float, seed: int = 42) -> Cuts:
    """Cuts of the named buckets into pieces of about half of ``target`` rows.

    ``keys`` has the order columns and the bucket. The sample is sorted where it
    lies and only the cuts, at most two a piece, come to the driver. A row that
    the sample holds in several places gets a cut on either side.
    """
    kinds = [keys.schema[c].dataType for c in key.columns()]
    wanted = {int(b): int(np.ceil(2 * n / target)) for b, n in rows.items()}
    fractions = {b: min(1.0, 1.3 * PER_PIECE * wanted[b] / max(n, 1)) for b, n in rows.items()}
    pieces = np.zeros(max(wanted) + 1, np.int64)
    pieces[list(wanted)] = list(wanted.values())
    sample = keys.select(BUCKET, *key.columns()).where(F.col(BUCKET).isin(list(wanted))).sampleBy(BUCKET, fractions, seed)
    within = Window.partitionBy(BUCKET)
    step = F.element_at(int_array(pieces), F.col(BUCKET) + 1)
    at = lambda i: F.floor(i * step / F.col("__n"))
    ranked = sample.withColumn("__i", F.row_number().over(within.orderBy(*key.order())) - 1).withColumn("__n", F.count("*").over(within))
    picked = ranked.where((F.col("__i") > 0) & (at(F.col("__i")) > at(F.col("__i") - 1)))
    places = picked.groupBy(BUCKET, *key.columns()).agg(F.count("*").alias("__n")).orderBy(BUCKET, *key.order())
    texts = [_text(c, kind).alias(f"t{i}") for i, (c, kind) in enumerate(zip(key.columns(), kinds, strict=True))]
    found = [(r[0], tuple(r[2:]), beyond) for r in places.select(BUCKET, "__n", *texts).collect() for beyond in range(2 if r["__n"] > 1 else 1)]
    if key.ascending and isinstance(kinds[0], (T.StringType, T.BinaryType)):
        found = _shortened(found)
    per = {b: sum(c[0] == b for c in found) for b in wanted}
    return Cuts(key, kinds, found, per)


def _shortened(found: list[tuple[int, tuple[str | None, ...], int]]) -> list[tuple[int, tuple[str | None, ...], int]]:
    """Cuts whose key is the least prefix beyond the cut before, so that plans don't hold whole texts; keys with cuts on either side stay whole."""
    out = []
    for i, (b, (text, *ties), beyond) in enumerate(found):
        before = found[i - 1][1][0] if i and found[i - 1][0] == b else ""
        paired = beyond or (i + 1 < len(found) and found[i + 1][:2] == found[i][:2])
        if text and before is not None and before != text and not paired:
            raw, last = bytes.fromhex(text), bytes.fromhex(before)
            n = next((j for j, (x, y) in enumerate(zip(raw, last)) if x != y), min(len(raw), len(last))) + 1
            while n < len(raw) and raw[n] & 0xC0 == 0x80:  # whole characters
                n += 1
            text = raw[:n].hex().upper()
        out.append((b, (text, *ties), beyond))
    return out


def count_pieces(keys: DataFrame, cuts: Cuts, buckets: list[int]) -> list[tuple[int, int, bool]]:
    """Fine bucket, exact rows, and whether all of them are alike in key and ties, for the pieces of the named buckets."""
    order = F.struct(*cuts.key.columns())
    fine = cuts.attach(keys.select(BUCKET, *cuts.key.columns()).where(F.col(BUCKET).isin(buckets)))
    found = fine.groupBy(BUCKET).agg(F.count("*").alias("n"), F.min(order).eqNullSafe(F.max(order)).alias("alike"))
    return [(r[BUCKET], r["n"], r["alike"]) for r in found.collect()]  # a row a piece
