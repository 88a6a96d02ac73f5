"""Proofs on results: order and content."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from modelsort.functions.keys import KeySpec, order_bits_np
from modelsort.operators.sorters import SortedFrame
from modelsort.plans.partitioner import PART


def _comes_before(a: Column, b: Column, key: KeySpec) -> Column:
    """Whether key ``a`` stands strictly before ``b`` in the order asked for."""
    null = a.isNull() & b.isNotNull() if key.nulls_first else a.isNotNull() & b.isNull()
    return F.when(a.isNull() | b.isNull(), null).otherwise(a < b if key.ascending else a > b)


def _neighbours(values: pa.Array, key: KeySpec) -> tuple[int, int]:
    """How many neighbours differ and how many fall, by the rules of ``_comes_before``; NaN is above all numbers and -0.0 equals 0.0."""
    if pa.types.is_floating(values.type):
        values = pa.array(order_bits_np(values.fill_null(0.0).to_numpy(zero_copy_only=False).astype(float)), mask=values.is_null().to_numpy(zero_copy_only=False))
    elif pa.types.is_boolean(values.type):
        values = values.cast(pa.int8())
    last, here = values.slice(0, len(values) - 1), values.slice(1)
    same, fall = pc.equal(here, last), (pc.less if key.ascending else pc.greater)(here, last)
    if values.null_count:
        same = pc.or_(same.fill_null(False), pc.and_(here.is_null(), last.is_null()))
        null = pc.and_(here.is_null(), last.is_valid()) if key.nulls_first else pc.and_(here.is_valid(), last.is_null())
        fall = pc.or_(fall.fill_null(False), null)
    return len(same) - same.true_count, fall.true_count


def _falls(sf: SortedFrame) -> DataFrame:
    """Runs of rows of one part as they lie, in order: rows, key changes and falls of neighbours, the first key, and the end of the run before.

    Each partition is walked once where it lies, a batch and one key in memory; nothing is moved or sorted but a row a run.
    """
    key = sf.key
    kind = sf.df.schema[key.column].dataType
    counts = [T.StructField(c, T.LongType()) for c in ("n", "rows", "keys", "falls")]
    schema = T.StructType([T.StructField(PART, T.LongType()), *counts, T.StructField("first", kind), T.StructField("last", kind)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, now = TaskContext.get().partitionId() << 33, None
        first = last = None

        def ended() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([*(pa.array([c], pa.int64()) for c in now), first, last], names=schema.names)

        for batch in batches:
            part, values = batch.column(0).to_numpy(), batch.column(1)
            edges = np.concatenate([[0], np.flatnonzero(np.diff(part)) + 1, [len(part)]]).tolist() if len(part) else [0]
            for a, b in zip(edges[:-1], edges[1:], strict=True):
                piece = values.slice(a, b - a)
                if now is not None and now[0] != part[a]:
                    yield ended()
                    now = None
                if now is None:
                    now, first = [int(part[a]), at + a, 0, 1, 0], piece.slice(0, 1)
                else:
                    piece = pa.concat_arrays([last, piece])
                changed, fell = _neighbours(piece, key)
                now = [*now[:2], now[2] + b - a, now[3] + changed, now[4] + fell]
                last = pa.concat_arrays([piece.slice(len(piece) - 1)])
            at += len(part)
        if now is not None:
            yield ended()

    runs = sf.df.select(F.col(PART).cast("long").alias(PART), F.col(key.column).alias("v")).mapInArrow(run, schema)
    along = Window.orderBy(PART, "n")  # a row a run
    return runs.withColumn("border", F.lag(F.struct(PART, F.col("last").alias("v"))).over(along))


def _at_border(sf: SortedFrame, inner: bool) -> Column:
    """Falls from the end of a run to the next one, of the same part or of another."""
    same = F.col("border")[PART] == F.col(PART)
    return F.count(F.when(F.col("border").isNotNull() & (same if inner else ~same) & _comes_before(F.col("first"), F.col("border")["v"], sf.key), 1))


def descents(sf: SortedFrame) -> DataFrame:
    """Falls within parts, as the rows lie, and between the ends of neighbouring parts; both 0 for a right sort."""
    within = F.coalesce(F.sum("falls"), F.lit(0)) + _at_border(sf, True)
    return _falls(sf).agg(within.cast("long").alias("within_parts"), _at_border(sf, False).alias("between_parts"))


def proof(sf: SortedFrame) -> DataFrame:
    """Rows, distinct keys and falls of a sorted frame as its rows lie, in one pass."""
    shared = F.count(F.when(F.col("border").isNotNull() & F.col("first").eqNullSafe(F.col("border")["v"]), 1))
    total = lambda c: F.coalesce(F.sum(c), F.lit(0))
    fell = total("falls") + _at_border(sf, True) + _at_border(sf, False)
    return _falls(sf).agg(total("rows").cast("long").alias("rows"), (total("keys") - shared).cast("long").alias("keys"), fell.cast("long").alias("descents"))


def same_bag(a: DataFrame, b: DataFrame) -> bool:
    """Whether two frames hold the same rows as often: counts and order-free sums of row hashes."""
    mark = lambda df: df.select(F.xxhash64(*sorted(df.columns)).alias("h")).agg(F.count("*"), F.sum(F.pmod("h", F.lit((1 << 31) - 1))), F.sum(F.pmod("h", F.lit(1_000_003)))).first()
    return tuple(mark(a)) == tuple(mark(b))
