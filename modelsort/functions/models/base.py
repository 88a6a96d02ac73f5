"""What all bucket models share, equality buckets for heavy keys, and models within buckets."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.functions.literals import double_array, int_array


class Model:
    """A non-decreasing map from a finite or infinite double to ``range(buckets)``."""

    buckets: int

    def column(self, x: Column) -> Column:
        """Bucket as an integer column; null and NaN inputs are the caller's concern."""
        raise NotImplementedError

    def attach(self, df: DataFrame, x: str, name: str) -> DataFrame:
        """Add the bucket of column ``x``."""
        return df.withColumn(name, self.column(F.col(x)))

    def predict(self, x: np.ndarray) -> np.ndarray:
        """The same on an array; used on samples only."""
        raise NotImplementedError

    def equality_buckets(self) -> set[int]:
        """Buckets that hold one key by construction."""
        return set()


def balanced_case(x: Column, splitters: list[float], low: int, high: int) -> Column:
    """How many of ``splitters[low:high]`` are below ``x``, plus ``low``, as nested comparisons."""
    if low == high:
        return F.lit(low)
    middle = (low + high) // 2
    return F.when(x > F.lit(splitters[middle]), balanced_case(x, splitters, middle + 1, high)).otherwise(balanced_case(x, splitters, low, middle))


@dataclass
class WithHeavy(Model):
    """A model whose heavy keys have buckets of their own, between those of smaller and larger keys.

    Each heavy key below a value moves the value two buckets up: one for the
    key itself, one for what lies above it within the same bucket.
    """

    inner: Model
    heavy: np.ndarray

    @property
    def buckets(self) -> int:
        return self.inner.buckets + 2 * len(self.heavy)

    def equality_buckets(self) -> set[int]:
        return {int(b) for b in self.predict(self.heavy)}

    def column(self, x: Column) -> Column:
        keys = self.heavy.tolist()
        is_heavy = x.isin(keys).cast("int") if keys else F.lit(0)
        return (self.inner.column(x) + 2 * balanced_case(x, keys, 0, len(keys)) + is_heavy).cast("int")

    def predict(self, x: np.ndarray) -> np.ndarray:
        below = np.searchsorted(self.heavy, x)
        return self.inner.predict(x) + 2 * below + np.isin(x, self.heavy)


@dataclass
class Composite(Model):
    """A root model with child models in some of its buckets, numbered densely in key order."""

    root: Model
    children: dict[int, Model]

    def __post_init__(self) -> None:
        widths = np.ones(self.root.buckets, np.int64)
        for b, child in self.children.items():
            widths[b] = child.buckets
        self.starts = np.cumsum(widths) - widths
        self.buckets = int(widths.sum())

    def attach(self, df: DataFrame, x: str, name: str) -> DataFrame:
        """Add the bucket of column ``x``; the root's bucket is a column of its own, so that deep models stay small."""
        root = f"{name}_root"
        return self.root.attach(df, x, root).withColumn(name, self._within(F.col(root), F.col(x))).drop(root)

    def column(self, x: Column) -> Column:
        return self._within(self.root.column(x), x)

    def _within(self, root: Column, x: Column) -> Column:
        from modelsort.functions.models.linear import LinearBucket
        from modelsort.functions.models.radix import RadixBucket

        start = F.element_at(int_array(self.starts), root + 1)
        if all(isinstance(c, LinearBucket) and c.slope >= 0 and not c.mirror for c in self.children.values()):
            lines = [self.children.get(b) for b in range(self.root.buckets)]
            pick = lambda f, none: F.element_at(double_array(f(c) if c else none for c in lines), root + 1)
            slope, base = pick(lambda c: c.slope, 0.0), pick(lambda c: c.intercept, 0.0)
            line = F.floor(slope * F.greatest(F.lit(-1e300), F.least(F.lit(1e300), x)) + base).cast("double")
            within = F.least(pick(lambda c: float(c.k - 1), 0.0), F.greatest(F.lit(0.0), line))
            return (start + within.cast("int")).cast("int")
        if all(isinstance(c, RadixBucket) for c in self.children.values()):
            digits = [self.children.get(b) or RadixBucket(0, 0, 1) for b in range(self.root.buckets)]
            part = lambda f: F.element_at(int_array(map(f, digits)), root + 1)
            digit = F.call_function("shiftright", RadixBucket.whole(x), part(lambda c: c.shift).cast("int"))
            within = F.least(part(lambda c: c.digits - 1), F.greatest(F.lit(0), digit - part(lambda c: c.base)))
            return (start + within).cast("int")
        within = F.lit(0)
        for b, child in self.children.items():
            within = F.when(root == b, child.column(x)).otherwise(within)
        return (start + within).cast("int")

    def predict(self, x: np.ndarray) -> np.ndarray:
        root = self.root.predict(x)
        out = self.starts[root]
        for b, child in self.children.items():
            mine = root == b
            out[mine] += child.predict(x[mine])
        return out
