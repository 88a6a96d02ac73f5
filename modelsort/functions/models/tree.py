"""Splitter trees: sample quantiles as a balanced search tree, with equality buckets."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.functions.literals import double_array
from modelsort.functions.models.base import Model, balanced_case
from modelsort.functions.sampling import equidistant


@dataclass
class SplitterTree(Model):
    """Buckets between distinct sorted splitters; a key equal to a splitter goes left of it.

    ``mode`` picks how buckets are attached: ``case`` nests comparisons, ``heap``
    walks an implicit heap in as many projections as it has levels, ``arrow``
    searches batches of keys. With ``equality`` every splitter in ``heavy`` gets
    a bucket of keys equal to it, right after those below it.
    """

    splitters: np.ndarray
    heavy: np.ndarray
    mode: str = "heap"

    @classmethod
    def fit(cls, sample: np.ndarray, k: int, equality: bool = True, mode: str = "heap") -> SplitterTree:
        picked, counts = np.unique(equidistant(sample, k), return_counts=True)
        return cls(picked, picked[counts > 1] if equality else np.zeros(0), mode)

    @classmethod
    def fit_distributed(cls, keys: DataFrame, x: str, k: int, mode: str = "heap") -> SplitterTree:
        """The same splitters of all keys of a column, looked up by rank; only they come to the driver."""
        from modelsort.operators.rank import ranked_keys
        from modelsort.plans.durable import materialize

        ranked = materialize(ranked_keys(keys.select(F.col(x).cast("double").alias("x"))), "ranked-keys")
        n = ranked.count()
        at = [j * n // k for j in range(1, k)] if n else []
        found = {r["rank"]: r["x"] for r in ranked.where(F.col("rank").isin(sorted(set(at)))).collect()} if at else {}
        picked, counts = np.unique(np.array([found[i] for i in at], float), return_counts=True)
        return cls(picked, picked[counts > 1], mode)

    @classmethod
    def from_sketch(cls, df: DataFrame, x: Column, k: int, accuracy: int = 10_000, mode: str = "heap") -> SplitterTree:
        """Splitters from the built-in quantile sketch instead of a sample."""
        found = df.agg(F.percentile_approx(x, [i / k for i in range(1, k)], accuracy)).first()[0] or []
        return cls(np.unique(np.array(found, float)), np.zeros(0), mode)

    @property
    def buckets(self) -> int:
        return len(self.splitters) + 1 + len(self.heavy)

    def joined(self, children: list[SplitterTree]) -> SplitterTree:
        """One tree of its splitters and those of trees within its buckets."""
        trees = [self, *children]
        return SplitterTree(np.unique(np.concatenate([t.splitters for t in trees])), np.unique(np.concatenate([t.heavy for t in trees])), self.mode)

    def equality_buckets(self) -> set[int]:
        return {int(b) for b in self.predict(self.heavy)}

    def _heap(self) -> tuple[list[float], int]:
        """Splitters in heap order, filled with infinity to a full tree."""
        levels = max(1, int(np.ceil(np.log2(len(self.splitters) + 1))))
        filled = np.append(self.splitters, np.full(2**levels - 1 - len(self.splitters), np.inf))
        heap = np.empty(2**levels - 1)
        for level in range(levels):
            width = 2**level
            step = 2 ** (levels - level)
            heap[width - 1 : 2 * width - 1] = filled[np.arange(width) * step + step // 2 - 1]
        return heap.tolist(), levels

    def _plain(self, x: Column) -> Column:
        keys = self.splitters.tolist()
        if not keys:
            return F.lit(0)
        if self.mode == "case":
            return balanced_case(x, keys, 0, len(keys))
        if self.mode == "arrow":
            splitters = self.splitters

            def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
                for values in batches:
                    v = values.fill_null(float("nan")).to_numpy(zero_copy_only=False).astype(float)
                    yield pa.array(np.searchsorted(splitters, v, side="left").astype(np.int32))

            run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
            return F.arrow_udf(run, "int")(x)
        return balanced_case(x, keys, 0, len(keys))

    def attach(self, df: DataFrame, x: str, name: str) -> DataFrame:
        """Add the bucket of column ``x``; heap mode takes one projection per level, all within code generation."""
        if self.mode != "heap" or not len(self.splitters):
            return super().attach(df, x, name)
        heap, levels = self._heap()
        array = double_array(heap)
        df = df.withColumn("__node", (F.lit(2) + (F.col(x) > F.element_at(array, F.lit(1))).cast("int")))
        for _ in range(levels - 1):
            df = df.withColumn("__node", 2 * F.col("__node") + (F.col(x) > F.element_at(array, F.col("__node"))).cast("int"))
        plain = F.least(F.col("__node") - F.lit(2**levels), F.lit(len(self.splitters)))
        return df.withColumn(name, self._with_equality(plain, F.col(x))).drop("__node")

    def column(self, x: Column) -> Column:
        return self._with_equality(self._plain(x), x)

    def _with_equality(self, plain: Column, x: Column) -> Column:
        if not len(self.heavy):
            return plain.cast("int")
        keys = self.heavy.tolist()
        # Every heavy splitter below the key adds its equality bucket; a heavy key itself goes one further.
        return (plain + balanced_case(x, keys, 0, len(keys)) + x.isin(keys).cast("int")).cast("int")

    def predict(self, x: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.splitters, x, side="left") + np.searchsorted(self.heavy, x, side="left") + np.isin(x, self.heavy)
