"""Most significant digits of an order-preserving integer."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from modelsort.functions.models.base import Model

#: The largest double below 2**63.
_MOST = 9223372036854774784.0


@dataclass
class RadixBucket(Model):
    """``floor(x) >> shift`` from its least value on; nothing is trained but the range.

    Digits are shifted before they are subtracted, so a range over 63 bits can't overflow.
    """

    base: int
    shift: int
    digits: int

    @classmethod
    def fit(cls, low: float, high: float, bits: int = 8) -> RadixBucket:
        a, b = (int(np.floor(np.clip(v, -_MOST, _MOST))) for v in (low, high))
        shift = max(0, (b - a).bit_length() - bits)
        return cls(a >> shift, shift, (b >> shift) - (a >> shift) + 1)

    @property
    def buckets(self) -> int:
        return self.digits

    @staticmethod
    def whole(x: Column) -> Column:
        """The integer whose digits are read."""
        return F.floor(F.least(F.greatest(x, F.lit(-_MOST)), F.lit(_MOST))).cast("long")

    def column(self, x: Column) -> Column:
        digit = F.shiftright(self.whole(x), self.shift)
        return (F.least(F.lit(self.base + self.digits - 1), F.greatest(F.lit(self.base), digit)) - F.lit(self.base)).cast("int")

    def predict(self, x: np.ndarray) -> np.ndarray:
        digit = np.floor(np.clip(x, -_MOST, _MOST)).astype(np.int64) >> self.shift
        return np.clip(digit, self.base, self.base + self.digits - 1) - self.base
