"""One bounded line per partitioning step, and the ways to fit it."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from modelsort.functions.models.base import Model


@dataclass
class LinearBucket(Model):
    """floor(slope * x + intercept), kept within ``range(k)``. ``conflict`` is the degree the fit accepted."""

    slope: float
    intercept: float
    k: int
    conflict: int | None = None
    mirror: bool = False

    def __post_init__(self) -> None:
        if not (np.isfinite(self.slope) and np.isfinite(self.intercept)) or self.slope < 0:
            raise ValueError("a bucket line must be finite and must not fall")
        self.buckets = self.k

    def column(self, x: Column) -> Column:
        # Floor gives a long; an infinite or huge product is brought into range as a double first.
        line = F.lit(self.slope) * x + F.lit(self.intercept)
        held = F.least(F.lit(float(self.k - 1)), F.greatest(F.lit(0.0), line)) if self.slope else F.lit(min(max(self.intercept, 0.0), self.k - 1.0))
        bucket = F.floor(held).cast("int")
        return F.lit(self.k - 1) - bucket if self.mirror else bucket

    def predict(self, x: np.ndarray) -> np.ndarray:
        line = self.slope * x + self.intercept if self.slope else np.full(len(x), self.intercept)
        bucket = np.floor(np.clip(line, 0, self.k - 1)).astype(np.int64)
        return self.k - 1 - bucket if self.mirror else bucket

    def mirrored(self) -> LinearBucket:
        """The same line for descending order."""
        return LinearBucket(self.slope, self.intercept, self.k, self.conflict, not self.mirror)

    @classmethod
    def constant(cls, k: int = 1) -> LinearBucket:
        return cls(0.0, 0.0, max(k, 1), 0)

    @classmethod
    def fit_min_max(cls, sample: np.ndarray, k: int) -> LinearBucket:
        """Equal key ranges between the least and the largest sampled key."""
        if not len(sample) or sample[0] == sample[-1]:
            return cls.constant(1)
        slope = k / (sample[-1] - sample[0])
        return cls(float(slope), float(-slope * sample[0]), k) if np.isfinite(slope) else cls.constant(1)

    @classmethod
    def fit_lsq(cls, sample: np.ndarray, k: int) -> LinearBucket:
        """Least squares on the target bucket k * rank / S."""
        if not len(sample) or sample[0] == sample[-1]:
            return cls.constant(1)
        target = k * np.arange(len(sample)) / len(sample)
        x = sample - sample.mean()
        with np.errstate(all="ignore"):  # keys too close for a finite slope fall back below
            slope = float((x * (target - target.mean())).sum() / (x * x).sum())
        return cls(slope, float(target.mean() - slope * sample.mean()), k) if np.isfinite(slope) and slope >= 0 else cls.fit_min_max(sample, k)

    @classmethod
    def fit_min_conflict(cls, sample: np.ndarray, k: int) -> LinearBucket:
        """The line of least conflict degree on a sorted sample.

        A degree D is feasible if keys D apart in the sample differ by a bucket
        width or more, the width being the span from the D-th to the D-th last
        key over k - 2. A larger D only widens gaps and narrows the span, so
        feasibility is monotone and the least D is found by bisection. If no D up
        to a third of the sample is feasible, that third is taken. The line sends
        the D-th key to 1 and the D-th last to k - 1.
        """
        s = len(sample)
        if not s or sample[0] == sample[-1]:
            return cls.constant(1)
        if k < 3 or s < 4:
            return cls.fit_min_max(sample, k)

        def width(d: int) -> float:
            return float(sample[s - 1 - d] - sample[d]) / (k - 2)

        def feasible(d: int) -> bool:
            return bool((sample[d:] - sample[: s - d]).min() >= width(d))

        low, high = 1, s // 3
        while low < high:
            middle = (low + high) // 2
            low, high = (low, middle) if feasible(middle) else (middle + 1, high)
        degree = low
        span = width(degree)
        if span <= 0 or not np.isfinite(1 / span):
            return cls.fit_min_max(sample, k)
        slope = 1 / span
        return cls(slope, float(1 - slope * sample[degree]), k, degree)

    @classmethod
    def fit_balanced(cls, sample: np.ndarray, k: int, rounds: int = 60) -> LinearBucket:
        """Local search on the sum of squared bucket deviations, from the better of three other fits."""
        if not len(sample) or sample[0] == sample[-1]:
            return cls.constant(1)

        def cost(line: LinearBucket) -> float:
            return float(((np.bincount(line.predict(sample), minlength=line.k) - len(sample) / line.k) ** 2).sum())

        best = min((f(sample, k) for f in (cls.fit_min_conflict, cls.fit_lsq, cls.fit_min_max)), key=cost)
        now, step = cost(best), 0.25
        for _ in range(rounds):
            middle = (k / 2 - best.intercept) / best.slope if best.slope else 0.0
            tries = []
            for turn in (1 - step, 1, 1 + step):
                for shift in (-step * k / 4, 0, step * k / 4):
                    slope = best.slope * turn
                    tries.append(cls(slope, k / 2 - slope * middle + shift, k, best.conflict))
            trial = min(tries, key=cost)
            if cost(trial) < now:
                best, now = trial, cost(trial)
            else:
                step /= 2
                if step < 1e-4:
                    break
        return best


FITS = {"min_conflict": LinearBucket.fit_min_conflict, "lsq": LinearBucket.fit_lsq, "minmax": LinearBucket.fit_min_max, "balanced": LinearBucket.fit_balanced}


def min_conflict_distributed(keys: DataFrame, x: str, k: int) -> LinearBucket:
    """The same least-conflict line for a sample too large for the driver.

    ``keys`` has a numeric column ``x``. Ranks are written once; a feasibility
    test is a join of ranks D apart, and bisection makes logarithmically many.
    """
    from modelsort.operators.rank import ranked_keys
    from modelsort.plans.durable import materialize

    ranked = materialize(ranked_keys(keys.select(F.col(x).cast("double").alias("x"))), "ranked-sample")
    s, low_key, high_key = ranked.agg(F.count("*"), F.min("x"), F.max("x")).first()
    if not s or low_key == high_key:
        return LinearBucket.constant(1)
    if k < 3 or s < 4:
        return LinearBucket.fit_min_max(np.array([low_key, high_key]), k)

    def ends(d: int) -> tuple[float, float]:
        found = {r["rank"]: r["x"] for r in ranked.where(F.col("rank").isin(d, s - 1 - d)).collect()}
        return found[d], found[s - 1 - d]

    def gap(d: int) -> float:
        later = ranked.select((F.col("rank") - d).alias("rank"), F.col("x").alias("y"))
        return ranked.join(later, "rank").agg(F.min(F.col("y") - F.col("x"))).first()[0]

    low, high = 1, s // 3
    while low < high:
        middle = (low + high) // 2
        a, b = ends(middle)
        low, high = (low, middle) if gap(middle) >= (b - a) / (k - 2) else (middle + 1, high)
    a, b = ends(low)
    span = (b - a) / (k - 2)
    if span <= 0:
        return LinearBucket.fit_min_max(np.array([low_key, high_key]), k)
    return LinearBucket(1 / span, 1 - (1 / span) * a, k, low)


def lsq_distributed(keys: DataFrame, x: str, k: int) -> LinearBucket:
    """Least squares on the target bucket k * rank / S of all keys, by aggregates over ranks that a partition sort gives."""
    from modelsort.operators.rank import ranked_keys
    from modelsort.plans.durable import materialize

    ranked = materialize(ranked_keys(keys.select(F.col(x).cast("double").alias("x"))), "ranked-keys")
    s, low_key, high_key, middle = ranked.agg(F.count("*"), F.min("x"), F.max("x"), F.avg("x")).first()
    if not s or low_key == high_key:
        return LinearBucket.constant(1)
    target = F.col("rank") * F.lit(k / s)
    slope, at_middle = ranked.select(target.alias("y"), (F.col("x") - F.lit(middle)).alias("x")).agg(F.regr_slope("y", "x"), F.regr_intercept("y", "x")).first()
    if slope is None or not np.isfinite(slope) or slope < 0:
        return LinearBucket.fit_min_max(np.array([low_key, high_key]), k)
    return LinearBucket(slope, at_middle - slope * middle, k)


def min_max_distributed(keys: DataFrame, x: str, k: int) -> LinearBucket:
    """Equal key ranges between the least and the largest of all keys."""
    ends = keys.select(F.col(x).cast("double").alias("x")).where(F.col("x").isNotNull() & ~F.isnan("x")).agg(F.min("x"), F.max("x")).first()
    return LinearBucket.fit_min_max(np.array([v for v in ends if v is not None]), k)


def lsq_by_group(df: DataFrame, group: str, x: str, k: int) -> DataFrame:
    """Least-squares lines per group from built-in regression aggregates."""
    w = Window.partitionBy(group)
    ranked = df.select(group, F.col(x).cast("double").alias("x")).withColumn("y", k * (F.row_number().over(w.orderBy("x")) - 1) / F.count("*").over(w))
    return ranked.groupBy(group).agg(F.regr_slope("y", "x").alias("slope"), F.regr_intercept("y", "x").alias("intercept"), F.count("*").alias("rows"))
