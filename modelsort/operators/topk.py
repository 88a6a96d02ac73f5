"""Selections that a bucket histogram answers without sorting all rows."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from modelsort.functions.keys import KeySpec, as_key, numeric, valid
from modelsort.functions.models import LinearBucket
from modelsort.operators.sorters import SortedFrame
from modelsort.plans.partitioner import BUCKET, assign


def _until(rows: np.ndarray, m: int) -> int:
    """Last bucket that holds any of the first ``m`` rows."""
    return int(min(len(rows) - 1, np.searchsorted(np.cumsum(rows), m)))


def smallest(df: DataFrame, sf: SortedFrame, m: int) -> DataFrame:
    """First ``m`` rows in the order of ``sf``; only rows of its first buckets are ranked."""
    near = assign(df, sf.key, sf.model).where(F.col(BUCKET) <= _until(sf.exact_sizes(df).rows, m)).drop(BUCKET)
    return near.orderBy(*sf.key.order()).limit(m)


def order_statistic(df: DataFrame, sf: SortedFrame, rank: int) -> float | None:
    """The key at 0-based ``rank``: the histogram names its bucket, which alone is sorted."""
    rows = sf.exact_sizes(df).rows
    before = np.cumsum(rows) - rows
    bucket = int(np.searchsorted(np.cumsum(rows), rank, side="right"))
    if bucket >= len(before):
        return None
    own = assign(df.select(sf.key.column), sf.key, sf.model).where(F.col(BUCKET) == bucket)
    row = own.orderBy(sf.key.order()[0]).offset(int(rank - before[bucket])).limit(1).first()
    return row[0] if row else None


def quantile(df: DataFrame, sf: SortedFrame, q: float) -> float | None:
    """Exact discrete quantile over non-null keys: the least key at or above the share ``q``."""
    sf.exact_sizes(df)
    nulls = int(sf.sizes.rows[0]) if sf.key.nulls_first else 0
    n = sf.sizes.n - int(sf.sizes.rows[0]) - int(sf.sizes.rows[-1])
    return order_statistic(df, sf, nulls + max(0, int(np.ceil(q * n)) - 1)) if n else None


def approx_quantile(df: DataFrame, key: str, q: float, accuracy: int = 10_000) -> DataFrame:
    return df.agg(F.percentile_approx(numeric(df, key), q, accuracy).alias("value"))


def model_quantile(sf: SortedFrame, q: float) -> float:
    """Quantile from bucket sizes alone, linear within the bucket; no data is read."""
    rows, low, high = sf.sizes.rows, sf.sizes.low, sf.sizes.high
    at = q * rows.sum()
    b = int(min(np.searchsorted(np.cumsum(rows), at), len(rows) - 1))
    within = (at - (rows[:b].sum())) / max(rows[b], 1)
    return float(low[b] + within * (high[b] - low[b]))


def per_group(df: DataFrame, group: str, key: str, m: int, ascending: bool = False, ties: tuple[str, ...] = ()) -> DataFrame:
    """The ``m`` first rows of each group with their ``rank``; Spark limits groups before the shuffle."""
    order = [F.col(key).asc() if ascending else F.col(key).desc(), *(F.col(t) for t in ties)]
    ranked = df.withColumn("rank", F.row_number().over(Window.partitionBy(group).orderBy(*order)))
    return ranked.where(F.col("rank") <= m)


def between(df: DataFrame, sf: SortedFrame, low, high) -> DataFrame:
    """Rows with a key in [low, high]: the model turns the range into buckets, the raw key decides."""
    key = as_key(sf.key)
    edges = df.sparkSession.createDataFrame([(low,), (high,)], f"{key.column} {df.schema[key.column].dataType.simpleString()}")
    a, b = (r[0] for r in assign(edges, sf.key, sf.model).select(BUCKET).collect())
    near = assign(df, sf.key, sf.model).where(F.col(BUCKET).between(min(a, b), max(a, b))).drop(BUCKET)
    return near.where(F.col(key.column).between(F.lit(low), F.lit(high)))


def isin(df: DataFrame, sf: SortedFrame, values: list) -> DataFrame:
    """Rows with one of the keys, looked for in the buckets of those keys only."""
    edges = df.sparkSession.createDataFrame([(v,) for v in values], f"{sf.key.column} {df.schema[sf.key.column].dataType.simpleString()}")
    buckets = sorted({r[0] for r in assign(edges, sf.key, sf.model).select(BUCKET).collect()})
    return assign(df, sf.key, sf.model).where(F.col(BUCKET).isin(buckets)).drop(BUCKET).where(F.col(sf.key.column).isin(values))


def clipped(df: DataFrame, key: KeySpec | str, line: LinearBucket) -> DataFrame:
    """Rows ``below`` and ``above`` the range that a line sends to buckets of its own."""
    x = numeric(df, key)
    bucket = F.lit(line.slope) * x + F.lit(line.intercept)
    return df.agg(F.count(F.when(valid(x) & (bucket < 0), 1)).alias("below"), F.count(F.when(valid(x) & (bucket >= line.k), 1)).alias("above"))


def where_payload(sf: SortedFrame, condition: Column | str) -> SortedFrame:
    """A sorted frame of the rows that meet a condition on any column; it reaches the scan below the shuffle."""
    return replace(sf, df=sf.df.where(condition), parted=sf.parted.where(condition), offsets=None, sizes=replace(sf.sizes, exact=False))
