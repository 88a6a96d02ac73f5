"""Recursion on models instead of data: buckets that stay too large get models of their own."""

from __future__ import annotations

import itertools
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from modelsort.functions import sampling
from modelsort.functions.keys import KeySpec, numeric
from modelsort.functions.models.base import Composite, Model
from modelsort.functions.models.tree import SplitterTree
from modelsort.plans.partitioner import Histogram, histogram

Fit = Callable[[np.ndarray, int], Model]


@dataclass
class Trace:
    """Largest open bucket after each round, rounds taken, and rows whose keys were looked at again."""

    largest: list[int] = field(default_factory=list)
    looked_at: list[int] = field(default_factory=list)

    @property
    def rounds(self) -> int:
        return len(self.largest)


def refine(df: DataFrame, key: KeySpec, model: Model, fit: Fit, k: int, limit: int, depth: int | None = None, share: float | None = None, seed: int = 42) -> tuple[Model, Histogram, Trace]:
    """Give every bucket of several numeric values and over ``limit`` rows a child model, all in one scan a round.

    Only keys are read; the payload moves once, after the last round. Without a
    ``depth`` rounds go on until no such bucket is left or the largest hardly gets
    smaller.
    """
    asc = key.plain()
    trace = Trace()
    x = numeric(df, asc)
    for level in itertools.count():
        hist = histogram(df, asc, model, share, seed)
        inner = hist.rows[1 : model.buckets + 1]
        open_ = (inner > limit) & ~hist.one_value()[1 : model.buckets + 1]
        trace.largest.append(int(inner[open_].max(initial=0)))
        stuck = level > 1 and trace.largest[-1] > 0.9 * trace.largest[-2]  # cuts by raw keys take over
        if level == depth or stuck or not open_.any():
            break
        sizes = {int(b): int(inner[b]) for b in np.flatnonzero(open_)}
        trace.looked_at.append(sum(sizes.values()))
        per = max(64, min(4 * k, sampling.sample_size(max(sizes.values()), k)))
        # Adds nothing, but keeps the filters on the bucket above the model, as in ``finish``.
        zero = F.shiftright(F.spark_partition_id(), 31)
        keys = model.attach(df.select(x.alias("x")).where(F.col("x").isNotNull() & ~F.isnan("x")), "x", "b").withColumn("b", F.col("b") + zero)
        samples = sampling.per_bucket(keys, F.col("x"), F.col("b"), sizes, per, seed + level)
        children = {}
        for b, sample in samples.items():
            low, high = hist.low[b + 1], hist.high[b + 1]
            child = fit(sample, max(3, min(k, int(np.ceil(4 * sizes[b] / limit)))))
            if len(np.unique(child.predict(np.array([low, high])))) == 1 and high > low and np.isfinite(high - low):
                child = fit(np.linspace(low, high, 64), max(3, k))
            children[b] = child
        trees = [c for c in (model, *children.values()) if isinstance(c, SplitterTree)]
        model = model.joined(trees[1:]) if len(trees) == len(children) + 1 else Composite(model, children)
    return model, hist, trace
