"""Training samples of keys: random, portable, per bucket, and what is picked from them."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Oversampling factor per binary logarithm of the rows.
OVERSAMPLING = 0.2


def alpha(n: int, c: float = OVERSAMPLING) -> float:
    """Oversampling factor; the base of the logarithm is taken as 2."""
    return c * math.log2(max(n, 2))


def sample_size(n: int, k: int, c: float = OVERSAMPLING) -> int:
    return max(1, math.ceil(alpha(n, c) * k) - 1)


def _collect(keys: DataFrame) -> np.ndarray:
    table = keys.toArrow()
    return np.sort(np.concatenate([np.zeros(0), *(c.to_numpy(zero_copy_only=False) for c in table.column(0).chunks)]).astype(float))


def draw(df: DataFrame, x: Column, size: int, n: int, seed: int = 42) -> np.ndarray:
    """About ``size`` sorted random keys of ``n``; a key-only scan, bounded by ``size`` on the driver."""
    fraction = min(1.0, 1.3 * size / max(n, 1) + 8 / max(n, 1))
    keys = df.select(x.alias("x")).where(F.col("x").isNotNull() & ~F.isnan("x") & (F.abs("x") < float("inf")))
    found = _collect(keys.sample(fraction, seed) if fraction < 1 else keys)
    if len(found) > size:
        found = np.sort(np.random.default_rng(seed).choice(found, size, replace=False))
    return found


def draw_fraction(df: DataFrame, x: Column, fraction: float = 0.01, seed: int = 42) -> np.ndarray:
    """Sorted sample of a share of the keys, for columns known to be small; ``Rmi.two_level_distributed`` holds no sample."""
    return _collect(df.select(x.alias("x")).where(F.col("x").isNotNull() & ~F.isnan("x")).sample(fraction, seed))


def modular(df: DataFrame, id_col: str, mult: int = 7919, mod: int = 10007, limit: int = 400) -> DataFrame:
    """A sample that any SQL engine draws alike: ids whose multiple falls under ``limit`` modulo ``mod``."""
    return df.where(F.pmod(F.col(id_col) * mult, F.lit(mod)) < limit)


def equidistant(sample: np.ndarray, k: int) -> np.ndarray:
    """k - 1 equally spaced keys of a sorted sample."""
    if not len(sample) or k < 2:
        return np.zeros(0)
    return sample[np.minimum(len(sample) - 1, (np.arange(1, k) * len(sample)) // k)]


def heavy_keys(sample: np.ndarray, k: int) -> np.ndarray:
    """Keys that hold more than twice a bucket's share of the sample, so at most k / 2 of them."""
    values, counts = np.unique(sample, return_counts=True)
    share = max(3.0, 2.0 * len(sample) / max(k, 1))
    return values[counts > share]


def per_bucket(df: DataFrame, x: Column, bucket: Column, sizes: dict[int, int], size: int, seed: int = 42) -> dict[int, np.ndarray]:
    """Sorted sample of about ``size`` keys of each named bucket, in one scan for all of them."""
    fractions = {b: min(1.0, 1.3 * size / max(n, 1)) for b, n in sizes.items()}
    rows = df.select(bucket.alias("b"), x.alias("x")).where(F.col("b").isin(list(sizes)) & ~F.isnan("x") & (F.abs("x") < float("inf")))
    table = rows.sampleBy("b", fractions, seed).toArrow()
    b, x_ = table.column("b").to_numpy(), table.column("x").to_numpy().astype(float)
    return {i: np.sort(x_[b == i]) for i in sizes}
