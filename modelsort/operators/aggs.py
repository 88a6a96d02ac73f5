"""Aggregates over sorted or bucketed keys, histograms, and fits per group."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.functions import sampling
from modelsort.functions.keys import numeric
from modelsort.functions.models import LinearBucket
from modelsort.operators.sorters import SortedFrame
from modelsort.plans.durable import materialize
from modelsort.plans.partitioner import PART


def sorted_group(sf: SortedFrame, *aggregates: Column) -> DataFrame:
    """Group by the sort key within parts; the scattered frame needs no further exchange."""
    return sf.df.groupBy(PART, sf.key.column).agg(*aggregates).drop(PART)


def distinct_count(sf: SortedFrame) -> DataFrame:
    """Distinct non-null keys: parts share none, so their counts add up."""
    return sf.df.groupBy(PART).agg(F.count_distinct(sf.key.column).alias("d")).agg(F.coalesce(F.sum("d"), F.lit(0)).cast("long").alias("distinct_keys"))


def approx_distinct(df: DataFrame, key: str) -> DataFrame:
    return df.agg(F.approx_count_distinct(key).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg(key)).alias("hll"))


def duplicate_ratio(df: DataFrame, key: str) -> DataFrame:
    return df.agg((1 - F.count_distinct(key) / F.count(key)).alias("duplicate_ratio"))


def heavy(df: DataFrame, key: str, phi: float) -> DataFrame:
    """Keys that hold ``phi`` of the rows or more with exact counts.

    Partial counts are combined before the shuffle, so a hot key costs a row a task.
    """
    n = df.count()
    return df.groupBy(key).agg(F.count("*").alias("rows")).where(F.col("rows") >= phi * n)


def histogram(df: DataFrame, key: str, bins: int, kind: str = "width", model: LinearBucket | None = None) -> DataFrame:
    """Rows per bin: ``width`` (equal ranges), ``depth`` (sample quantiles) or ``model`` (a bucket line)."""
    x = numeric(df, key)
    if kind == "model":
        bin_ = (model or LinearBucket.constant(1)).column(x)
    elif kind == "width":
        low, high = df.agg(F.min(x), F.max(x)).first()
        bin_ = F.least(F.lit(bins), F.width_bucket(x, F.lit(low), F.lit(high), F.lit(bins))) - 1 if low is not None and low < high else F.lit(0)
    else:
        n = df.count()
        cuts = np.unique(sampling.equidistant(sampling.draw(df, x, 64 * bins, max(n, 1)), bins)).tolist()
        bin_ = F.size(F.filter(F.array(*(F.lit(c) for c in cuts)), lambda c: c < x)) if cuts else F.lit(0)
    return df.where(x.isNotNull()).groupBy(bin_.cast("int").alias("bin")).agg(F.count("*").alias("rows"))


def line(df: DataFrame, y: Column, x: Column) -> DataFrame:
    """Least-squares line and its fit from built-in aggregates."""
    return df.agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"), F.covar_pop(y, x).alias("covariance"))


def fit_per_group(df: DataFrame, group: str, key: str, k: int = 256, sample_rows: int = 100_000, seed: int = 42) -> DataFrame:
    """Least-conflict line of every group, from about ``sample_rows`` keys of each at most.

    Sizes are sent to every task if they are counted few, so that keys are sampled
    before they are shuffled.
    """
    sizes = materialize(df.groupBy(group).agg(F.count("*").alias("__n")), "group-sizes")
    sizes = F.broadcast(sizes) if sizes.count() <= 100_000 else sizes
    keys = df.select(group, numeric(df, key).alias("x")).where("x is not null").join(sizes, group)
    few = keys.where(F.rand(seed) < F.lit(float(sample_rows)) / F.col("__n")).select(group, "x")
    kind = df.schema[group].dataType.simpleString()

    def fit(table: pa.Table) -> pa.Table:
        x = np.sort(table.column("x").to_numpy().astype(float))
        m = LinearBucket.fit_min_conflict(x, k)
        return pa.table({group: table.column(group)[:1], "slope": [m.slope], "intercept": [m.intercept], "buckets": pa.array([m.k], pa.int32()), "conflict": pa.array([m.conflict], pa.int32()), "keys": [len(x)]})

    return few.groupBy(group).applyInArrow(fit, f"`{group}` {kind}, slope double, intercept double, buckets int, conflict int, keys long")
