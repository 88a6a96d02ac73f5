"""Ordered lookups: a learned index with error bounds, and the binary search it replaces."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from modelsort.functions import sampling
from modelsort.functions.keys import KeySpec, numeric
from modelsort.functions.literals import int_array
from modelsort.functions.models import Rmi
from modelsort.operators.rank import global_position
from modelsort.operators.sorters import linear_partition_sort
from modelsort.plans.durable import materialize


#: Keys that a binary search keeps on the driver and in every task at most.
FENCES = 65_536


@dataclass
class RmiIndex:
    """Rows at their 0-based ``pos`` with a model; ``below`` and ``above`` bound how far each of its lines misses either way.

    ``error`` is the largest miss of all lines. A key visits the blocks within
    the bounds of its own line only, so one bad line doesn't widen the others.
    """

    table: DataFrame
    key: str
    model: Rmi
    below: np.ndarray
    above: np.ndarray
    n: int
    block: int

    @property
    def error(self) -> int:
        return int(max(self.below.max(initial=0), self.above.max(initial=0)))

    @classmethod
    def build(cls, df: DataFrame, key: str, ties: tuple[str, ...] = (), leaves: int = 64, block: int = 1024) -> RmiIndex:
        """Sort, number and write the rows, train on a sample, and measure the largest miss on all of them."""
        placed = global_position(linear_partition_sort(df, KeySpec(key, ties=ties)), "pos").withColumn("pos", F.col("pos") - 1)
        table = materialize(placed.where(F.col(key).isNotNull()).withColumn("block", F.floor(F.col("pos") / block).cast("long")), "index")
        n = table.count()
        x = numeric(table, key)
        sample = sampling.draw(table, x, 64 * leaves, max(n, 1))
        model = Rmi.two_level(sample, leaves).monotone(sample) if len(sample) else Rmi.fit(sample, [1])
        miss = F.col("pos") - F.floor(model.column(x) * n).cast("long")
        found = table.groupBy(model.leaf(x).alias("leaf")).agg(F.max(-miss).alias("below"), F.max(miss).alias("above")).collect()  # a row a line
        bounds = np.zeros((2, model.widths[-1]), np.int64)
        for r in found:
            bounds[:, r["leaf"]] = max(r["below"], 0), max(r["above"], 0)
        return cls(table, key, model, bounds[0], bounds[1], n, block)

    def lookup(self, keys: DataFrame) -> DataFrame:
        """Rows whose key is among ``keys`` (column of the same name), searched within the error bound.

        A key visits the blocks that its bound touches; block and raw key join.
        """
        x = numeric(keys, self.key)
        guess, leaf = F.floor(self.model.column(x) * self.n), self.model.leaf(x) + 1
        low = F.floor(F.greatest(F.lit(0), guess - F.element_at(int_array(self.below), leaf)) / self.block).cast("long")
        high = F.floor(F.greatest(F.lit(0), F.least(F.lit(max(self.n - 1, 0)), guess + F.element_at(int_array(self.above), leaf))) / self.block).cast("long")
        wanted = keys.where(F.col(self.key).isNotNull()).distinct().withColumn("block", F.explode(F.sequence(low, F.greatest(low, high))))
        # A key is many rows by now, which Spark's estimate doesn't see: they are sorted, not broadcast from the driver.
        return self.table.join(wanted.hint("merge"), ["block", self.key]).drop("block")


@dataclass
class BinarySearch:
    """First keys of runs of blocks, searched by bisection in Arrow batches; at most ``FENCES`` of them, whatever the rows."""

    firsts: np.ndarray
    table: DataFrame
    key: str

    @classmethod
    def build(cls, index: RmiIndex, fences: int = FENCES) -> BinarySearch:
        run = max(1, -(-(-(-index.n // index.block)) // fences))
        table = index.table.withColumn("block", F.floor(F.col("block") / run))
        found = table.groupBy("block").agg(F.min(numeric(index.table, index.key)).alias("x")).orderBy("block").toPandas()
        return cls(found["x"].to_numpy(float), table, index.key)

    def lookup(self, keys: DataFrame) -> DataFrame:
        firsts, x = self.firsts, numeric(keys, self.key)

        def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
            for values in batches:
                v = values.fill_null(float("nan")).to_numpy(zero_copy_only=False)
                low, high = np.searchsorted(firsts, v, "left") - 1, np.searchsorted(firsts, v, "right") - 1
                yield pa.array([list(range(max(a, 0), b + 1)) for a, b in zip(low.tolist(), high.tolist(), strict=True)], pa.list_(pa.int64()))

        run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
        wanted = keys.where(F.col(self.key).isNotNull()).distinct().withColumn("block", F.explode(F.arrow_udf(run, "array<long>")(x)))
        return self.table.join(wanted, ["block", self.key]).drop("block")
