"""A small simulator of in-place partitioning with per-bucket buffers, and its table function."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T
from pyspark.sql.functions import udtf
from pyspark.sql.pandas.types import to_arrow_schema

from modelsort.functions.models import LinearBucket, Model


@dataclass
class Blocks:
    """What classification leaves: full blocks in flush order, and each bucket's unfinished buffer."""

    flushed: list[tuple[int, list[float]]]
    left: dict[int, list[float]]
    sizes: list[int]
    peak: int

    def array(self) -> list[float]:
        """The array after classification: blocks, then what the buffers still hold."""
        return [x for _, block in self.flushed for x in block] + [x for b in sorted(self.left) for x in self.left[b]]

    def contiguous(self) -> list[list[float]]:
        """The array after blocks are permuted: every bucket's blocks, then its buffer."""
        return [[x for b, block in self.flushed if b == bucket for x in block] + self.left.get(bucket, []) for bucket in range(len(self.sizes))]


def classify(keys: list[float], model: Model, block: int) -> Blocks:
    """Send keys to buffers of ``block`` elements that are flushed when full; memory is one buffer a bucket."""
    buffers: dict[int, list[float]] = {}
    flushed, sizes, held, peak = [], [0] * model.buckets, 0, 0
    for key, bucket in zip(keys, model.predict(np.array(keys, float)).tolist(), strict=True):
        buffers.setdefault(bucket, []).append(key)
        sizes[bucket] += 1
        held += 1
        peak = max(peak, held)
        if len(buffers[bucket]) == block:
            flushed.append((bucket, buffers.pop(bucket)))
            held -= block
    return Blocks(flushed, buffers, sizes, peak)


def classify_groups(df: DataFrame, by: str, order: str, key: str, model: Model, block: int, take: Callable[[Blocks], list[tuple]], columns: str) -> DataFrame:
    """What ``take`` gives for the keys of each group ``by``, classified in the order of ``order``; ``columns`` is its schema.

    A group is one array and is held by one task. Keys must be numbers without null and NaN.
    """
    schema = T.StructType([df.schema[by], *T.StructType.fromDDL(columns)])
    kinds = to_arrow_schema(schema)

    def run(table: pa.Table) -> pa.Table:
        rows = take(classify(table.sort_by(order).column(key).to_pylist(), model, block))
        values = [pa.array(c) for c in zip(*rows, strict=True)]
        return pa.table([pa.repeat(table.column(by)[0], len(rows)), *values], kinds.names).cast(kinds)

    return df.select(by, order, key).groupBy(by).applyInArrow(run, schema)


@udtf(returnType="step int, bucket int, keys array<double>")
class BlockTrace:
    """Rows of a classification: flushed blocks by step, then buffers left over (step -1)."""

    def eval(self, keys: list[float], slope: float, intercept: float, k: int, block: int) -> Iterator[tuple]:
        found = classify(list(keys), LinearBucket(float(slope), float(intercept), k), block)
        for step, (bucket, held) in enumerate(found.flushed):
            yield step, bucket, [float(x) for x in held]
        for bucket in sorted(found.left):
            yield -1, bucket, [float(x) for x in found.left[bucket]]
