"""The partitioning framework that all sorters share: assign, count, pack, scatter."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.functions.keys import KeySpec, numeric, slotted
from modelsort.functions.literals import int_array
from modelsort.functions.models.base import Model
from modelsort.plans.cuts import BUCKET

PART, X = "__part", "__x"


def assign(df: DataFrame, key: KeySpec, model: Model) -> DataFrame:
    """Add the final bucket of each row, in output order; the numeric view is dropped again."""
    viewed = model.attach(df.withColumn(X, numeric(df, key)), X, BUCKET)
    return viewed.withColumn(BUCKET, slotted(F.col(BUCKET), F.col(X), model.buckets, key)).drop(X)


@dataclass
class Histogram:
    """Rows, least and largest numeric key of every bucket that has rows; not ``exact`` if scaled up from a sample."""

    rows: np.ndarray
    low: np.ndarray
    high: np.ndarray
    exact: bool = True

    @property
    def n(self) -> int:
        return int(self.rows.sum())

    def one_value(self) -> np.ndarray:
        """Buckets of one numeric value, which no numeric model can split; their raw keys may still differ."""
        return (self.rows > 0) & (self.low == self.high)


def histogram(df: DataFrame, key: KeySpec, model: Model, sample: float | None = None, seed: int = 42) -> Histogram:
    """Bucket sizes from a key-only scan: exact, or scaled up from a share of the rows.

    The driver holds a row per bucket. With far more buckets than rows per task
    a partial aggregate hardly shrinks anything; give ``sample`` then.
    """
    keys = df.select(key.column)
    if sample:
        keys = keys.sample(sample, seed)
    viewed = keys.withColumn(X, numeric(df, key))
    bucketed = model.attach(viewed, X, BUCKET).withColumn(BUCKET, slotted(F.col(BUCKET), F.col(X), model.buckets, key))
    found = bucketed.groupBy(BUCKET).agg(F.count("*").alias("rows"), F.min(X).alias("low"), F.max(X).alias("high")).toPandas()
    size = model.buckets + 3
    rows, low, high = np.zeros(size, np.int64), np.full(size, np.nan), np.full(size, np.nan)
    at = found[BUCKET].to_numpy(np.int64)
    rows[at] = np.round(found["rows"].to_numpy(float) / (sample or 1)).astype(np.int64)
    low[at], high[at] = found["low"].to_numpy(float), found["high"].to_numpy(float)
    return Histogram(rows, low, high, not sample)


@dataclass
class Packing:
    """Part of each bucket, and how many adjacent parts a bucket of rows alike in key and ties is spread over."""

    part: np.ndarray
    spread: np.ndarray
    parts: int


def pack(rows: np.ndarray, parts: int, splittable: np.ndarray | None = None, target: float | None = None) -> Packing:
    """Contiguous parts of about equal rows; buckets in ``splittable`` may span several whole parts."""
    target = target or max(1.0, rows.sum() / max(parts, 1))
    part, spread = np.zeros(len(rows), np.int64), np.ones(len(rows), np.int64)
    now, load = 0, 0.0
    for b, n in enumerate(rows.tolist()):
        if splittable is not None and splittable[b] and n >= 1.5 * target:
            now += load > 0
            spread[b] = int(np.ceil(n / target))
            part[b] = now
            now, load = now + int(spread[b]), 0.0
            continue
        if load and load + n / 2 > target:
            now, load = now + 1, 0.0
        part[b] = now
        load += n
    total = max(1, now + (load > 0))
    return Packing(np.minimum(part, total - 1), spread, total)  # empty buckets at the end open no part


def part_column(packing: Packing, salt: Column | None = None) -> Column:
    """Part of a bucket column, from literals; a spread bucket's rows go by ``salt``."""
    index = F.col(BUCKET) + 1
    part = F.element_at(int_array(packing.part), index)
    if salt is not None and (packing.spread > 1).any():
        part = part + F.pmod(salt, F.element_at(int_array(packing.spread), index)).cast("int")
    return part.cast("int")


def scatter(df: DataFrame, packing: Packing) -> DataFrame:
    """Move every row to the part of its bucket, once; bucket ids become partition ids without hashing."""
    return move(df.withColumn(PART, part_column(packing)).drop(BUCKET), packing.parts)


def move(parted: DataFrame, parts: int) -> DataFrame:
    return parted.repartitionById(parts, F.col(PART))


def spread_parts(assigned: DataFrame, packing: Packing, rows: np.ndarray, target: float, order: list[str]) -> tuple[DataFrame, np.ndarray, bool]:
    """Rows with their part where some buckets span parts, the rows of each part, and whether rows carry ``__copies``.

    All rows of a spread bucket are alike in key and ties, so any of them may
    go to any of its parts, as long as a repeated task decides alike: by the hash
    of the whole row, as counted first. Where that leaves lumps, since rows repeat
    as wholes, equal rows travel as one row with a number of copies, dealt in
    shares, and are laid out again after the shuffle.
    """
    wide = np.flatnonzero(packing.spread > 1).tolist()
    columns = [c for c in assigned.columns if c != BUCKET]
    hashed = [c for c in columns if not holds_map(assigned.schema[c].dataType)]
    salt = F.xxhash64(*hashed)
    per_part = np.bincount(packing.part, weights=np.where(packing.spread > 1, 0, rows), minlength=packing.parts).astype(np.int64)
    inside = F.col(BUCKET).isin(wide)
    parted = assigned.withColumn(PART, part_column(packing, salt)).drop(BUCKET)
    if set(columns) - set(order) or len(hashed) < len(columns):
        dealt = {r[PART]: r["count"] for r in assigned.where(inside).withColumn(PART, part_column(packing, salt)).groupBy(PART).count().collect()}  # a row a part
        if max(dealt.values(), default=0) <= 1.75 * target or len(hashed) < len(columns):
            for part, n in dealt.items():
                per_part[part] += n
            return parted, per_part, False
    # Floats are grouped as text, which keeps the sign of zero; their first value stands for all.
    alike = {c: F.col(c).cast("string") if assigned.schema[c].dataType.typeName() in ("double", "float") else F.col(c) for c in columns}
    whole = assigned.where(inside).groupBy(BUCKET, *(e.alias(f"__g{i}") for i, e in enumerate(alike.values()))).agg(F.count("*").alias("__n"), *(F.first(c).alias(c) for c in columns))
    share = int(min(1 << 16, max(1, target // 8)))
    pieces = whole.withColumn("__i", F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"(__n - 1) div {share}"))))
    pieces = pieces.withColumn(PART, part_column(packing, salt + F.col("__i"))).withColumn("__copies", F.least(F.lit(share).cast("long"), F.col("__n") - F.col("__i") * share).cast("int"))
    for r in pieces.groupBy(PART).agg(F.sum("__copies").alias("n")).collect():  # a row a part
        per_part[r[PART]] += r["n"]
    light = assigned.where(~inside).withColumn(PART, part_column(packing)).withColumn("__copies", F.lit(1))
    names = [*columns, PART, "__copies"]
    return light.select(*names).unionByName(pieces.select(*names)), per_part, True


def holds_map(kind) -> bool:
    """Whether a type holds a map or variant, which can't be hashed or grouped."""
    if kind.typeName() in ("map", "variant"):
        return True
    inner = [f.dataType for f in kind.fields] if kind.typeName() == "struct" else [kind.elementType] if kind.typeName() == "array" else []
    return any(map(holds_map, inner))


def utilisation(rows: np.ndarray, workers: int) -> float:
    """Share of the workers' time that is busy when sub-problems are taken in order by whoever is free."""
    loads = np.zeros(max(1, workers))
    for n in rows.tolist():
        loads[loads.argmin()] += n
    return float(loads.sum() / (len(loads) * loads.max())) if loads.max() else 1.0
