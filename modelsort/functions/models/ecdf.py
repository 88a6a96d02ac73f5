"""Empirical distribution functions as models, and any of them as a partitioner."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

from modelsort.functions.models.base import Model


@dataclass
class SampleEcdf:
    """Step function of a sorted sample, searched in Arrow batches."""

    sample: np.ndarray

    def predict(self, x: np.ndarray) -> np.ndarray:
        share = np.searchsorted(self.sample, x, side="right") / max(len(self.sample), 1)
        return np.minimum(share, np.nextafter(1, 0))

    def column(self, x: Column) -> Column:
        def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
            for values in batches:
                yield pa.array(self.predict(values.fill_null(float("nan")).to_numpy(zero_copy_only=False).astype(float)))

        run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
        return F.arrow_udf(run, "double")(x)


@dataclass
class EcdfBucket(Model):
    """floor(k * F(x)) for any eCDF model ``F`` with ``predict`` and ``column``."""

    ecdf: object
    k: int

    @property
    def buckets(self) -> int:
        return self.k

    def column(self, x: Column) -> Column:
        return F.least(F.lit(self.k - 1), F.floor(F.lit(float(self.k)) * self.ecdf.column(x)).cast("int"))

    def predict(self, x: np.ndarray) -> np.ndarray:
        return np.minimum(self.k - 1, np.floor(self.k * self.ecdf.predict(x)).astype(np.int64))
