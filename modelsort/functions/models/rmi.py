"""Recursive model indexes as eCDFs: small linear models that dispatch to others."""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.functions.literals import double_array


def _line(x: np.ndarray, y: np.ndarray, kind: str) -> tuple[float, float]:
    """Slope and intercept through the ends (``spline``, ``minmax``) or by least squares (``lsq``).

    Keys too close for a finite rising line get their mean share, which is always non-decreasing.
    """
    flat = 0.0, float(y.mean()) if len(y) else 0.0
    if len(x) < 2 or x[0] == x[-1]:
        return flat
    with np.errstate(all="ignore"):
        if kind == "lsq":
            d = x - x.mean()
            slope = (d * (y - y.mean())).sum() / (d * d).sum()
            intercept = y.mean() - slope * x.mean()
        elif kind == "minmax":
            slope = 1.0 / (x[-1] - x[0])
            intercept = -slope * x[0]
        else:
            slope = (y[-1] - y[0]) / (x[-1] - x[0])
            intercept = y[0] - slope * x[0]
    return (float(slope), float(intercept)) if 0 <= slope < np.inf and np.isfinite(intercept) else flat


@dataclass
class Rmi:
    """Levels of lines; each level's output picks the line of the next, the last gives the eCDF in [0, 1).

    ``bounds`` holds the range of each last-level line once the model is made
    monotone: no line leaves the share of the order that its keys have.
    """

    widths: list[int]
    slopes: list[np.ndarray]
    intercepts: list[np.ndarray]
    bounds: np.ndarray | None = None
    empty: int = 0

    @classmethod
    def fit(cls, sample: np.ndarray, widths: list[int], kinds: list[str] | None = None) -> Rmi:
        """Train on a sorted sample, level by level; an empty line carries on from its neighbour's end."""
        kinds = kinds or ["spline"] * len(widths)
        s = len(sample)
        y = np.arange(s) / max(s, 1)
        slopes, intercepts, owner, empty = [], [], np.zeros(s, np.int64), 0
        for level, (width, kind) in enumerate(zip(widths, kinds, strict=True)):
            a, b = np.zeros(width), np.zeros(width)
            cut = np.searchsorted(owner, np.arange(width + 1)) if s else np.zeros(width + 1, np.int64)
            last = 0.0
            for m in range(width):
                lo, hi = cut[m], cut[m + 1]
                if hi > lo:
                    a[m], b[m] = _line(sample[lo:hi], y[lo:hi], kind)
                    last = hi / s
                else:
                    a[m], b[m] = 0.0, last
                    empty += level == len(widths) - 1
            slopes.append(a)
            intercepts.append(b)
            if level + 1 < len(widths):
                out = np.clip(a[owner] * sample + b[owner], 0, np.nextafter(1, 0))
                owner = np.maximum.accumulate(np.floor(out * widths[level + 1]).astype(np.int64)) if s else owner
        return cls(list(widths), slopes, intercepts, None, int(empty))

    @classmethod
    def two_level(cls, sample: np.ndarray, m: int, root: str = "spline", leaf: str = "spline") -> Rmi:
        """A root line over ``m`` leaf lines, leaves by interpolation of their end points by default."""
        return cls.fit(sample, [1, m], [root, leaf])

    @classmethod
    def two_level_distributed(cls, keys: DataFrame, x: str, m: int) -> Rmi:
        """The two-level model of interpolated lines, already monotone, on keys of any number.

        The root runs through the ends of the keys; a leaf needs its keys' ends and
        count only, so the driver holds a row a leaf and never the keys.
        """
        n, low, high = keys.agg(F.count(x), F.min(x), F.max(x)).first()
        if not n or not low < high or not np.isfinite(high - low):
            return cls.two_level(np.array([v for v in (low, high) if v is not None]), 1).monotone(np.array([v for v in (low, high) if v is not None]))
        slope = (n - 1) / n / (high - low)
        root = cls([1], [np.array([slope])], [np.array([-slope * low])])
        leaf = F.floor(root.column(F.col(x)) * m).cast("int")
        found = keys.where(F.col(x).isNotNull()).groupBy(leaf.alias("leaf")).agg(F.count(x).alias("n"), F.min(x).alias("low"), F.max(x).alias("high")).toPandas().sort_values("leaf")  # a row a leaf
        counts = np.zeros(m, np.int64)
        at = found["leaf"].to_numpy(int)
        counts[at] = found["n"].to_numpy(np.int64)
        ends = np.concatenate([[0], np.cumsum(counts)]) / n
        a, b = np.zeros(m), ends[:-1].copy()
        for leaf_at, x0, x1 in zip(at.tolist(), found["low"].tolist(), found["high"].tolist(), strict=True):
            a[leaf_at], b[leaf_at] = _line(np.array([x0, x1]), np.array([ends[leaf_at], ends[leaf_at + 1] - 1 / n]), "spline")
        return cls([1, m], [root.slopes[0], a], [root.intercepts[0], b], np.stack([ends[:-1], ends[1:]], axis=1), int((counts == 0).sum()))

    def leaf(self, x: Column) -> Column:
        """Number of the last-level line that answers for a key."""
        held, owner = F.greatest(F.lit(-1e300), F.least(F.lit(1e300), x)), F.lit(0)
        for level in range(len(self.widths) - 1):
            line = F.element_at(double_array(self.slopes[level]), owner + 1) * held + F.element_at(double_array(self.intercepts[level]), owner + 1)
            share = F.least(F.lit(float(np.nextafter(1, 0))), F.greatest(F.lit(0.0), line))
            owner = F.floor(share * self.widths[level + 1]).cast("int")
        return owner

    def empty_leaves(self) -> float:
        return self.empty / self.widths[-1]

    def monotone(self, sample: np.ndarray) -> Rmi:
        """The same model with every leaf kept between the shares at which its keys begin and end."""
        owner = self._owner(sample)
        ends = np.searchsorted(owner, np.arange(self.widths[-1] + 1)) / max(len(sample), 1)
        ends = np.maximum.accumulate(ends)
        return Rmi(self.widths, self.slopes, self.intercepts, np.stack([ends[:-1], ends[1:]], axis=1), self.empty)

    def _owner(self, x: np.ndarray) -> np.ndarray:
        owner = np.zeros(len(x), np.int64)
        for level in range(len(self.widths) - 1):
            out = np.clip(self.slopes[level][owner] * x + self.intercepts[level][owner], 0, np.nextafter(1, 0))
            owner = np.floor(out * self.widths[level + 1]).astype(np.int64)
        return owner

    def predict(self, x: np.ndarray) -> np.ndarray:
        owner = self._owner(x)
        out = self.slopes[-1][owner] * x + self.intercepts[-1][owner]
        if self.bounds is not None:
            out = np.clip(out, self.bounds[owner, 0], self.bounds[owner, 1])
        return np.clip(out, 0, np.nextafter(1, 0))

    def column(self, x: Column) -> Column:
        """Predicted share of the order, from arrays of literals."""
        owner: Column = F.lit(0)
        top = F.lit(float(np.nextafter(1, 0)))
        x = F.greatest(F.lit(-1e300), F.least(F.lit(1e300), x))
        pick = lambda values, at: F.element_at(double_array(values), at + 1)
        for level, width in enumerate(self.widths):
            line = pick(self.slopes[level], owner) * x + pick(self.intercepts[level], owner)
            if level == len(self.widths) - 1:
                if self.bounds is not None:
                    line = F.least(pick(self.bounds[:, 1], owner), F.greatest(pick(self.bounds[:, 0], owner), line))
                return F.least(top, F.greatest(F.lit(0.0), line))
            held = F.least(top, F.greatest(F.lit(0.0), line))
            owner = F.floor(held * self.widths[level + 1]).cast("int")
        raise ValueError("a model needs a level")


def tune_rmi(sample: np.ndarray, leaves: tuple[int, ...] = (16, 64, 256, 1024), roots: tuple[str, ...] = ("spline", "lsq", "minmax"), leaf_kinds: tuple[str, ...] = ("spline", "lsq")) -> list[dict]:
    """Error and training time of every combination on a sample, best first; dear, so not used for sorting."""
    truth = np.searchsorted(sample, sample, side="right") / max(len(sample), 1)
    rows = []
    for m in leaves:
        for root in roots:
            for leaf in leaf_kinds:
                start = time.perf_counter()
                model = Rmi.two_level(sample, m, root, leaf)
                seconds = time.perf_counter() - start
                rows.append({"leaves": m, "root": root, "leaf": leaf, "mean_error": float(np.abs(model.predict(sample) - truth).mean()), "max_error": float(np.abs(model.predict(sample) - truth).max()), "seconds": seconds})
    return sorted(rows, key=lambda r: r["mean_error"])
