"""One partition sort, many models: every sorter is a fit plugged into the same steps.

Fitting reads keys only and happens when a sorter is called; the payload moves
in one shuffle when the result is used. Parts are ordered among each other and
sorted within, by the raw key, so any non-decreasing model gives an exact sort.
Buckets that no numeric model can split are cut by raw keys and ties, and only
rows alike in all of these are spread over parts freely.
"""

from __future__ import annotations

import itertools
import tempfile
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F
from pyspark.sql import types as T

from modelsort.functions import sampling
from modelsort.functions.keys import KeySpec, as_key, numeric, order_bits, order_bits_np, valid, with_prefix
from modelsort.functions.models import EcdfBucket, LinearBucket, Model, RadixBucket, Rmi, SplitterTree, WithHeavy
from modelsort.functions.models.linear import FITS
from modelsort.plans.cuts import count_pieces, find_cuts
from modelsort.plans.durable import materialize
from modelsort.plans.partitioner import BUCKET, PART, Histogram, Packing, assign, histogram, move, pack, part_column, spread_parts
from modelsort.plans.refine import Trace, refine

#: Buckets up to this many rows aren't cut, however many parts are asked for.
CUT_ROWS = 1024


@dataclass(frozen=True)
class SortConfig:
    """Parameters of a partition sort.

    ``k`` buckets a step, ``base_rows`` below which a bucket is left to the base
    case, ``parts`` of the result (by default the shuffle partitions), ``depth``
    refinement rounds at most (None: until every bucket is small or of one
    numeric value), ``equality`` buckets for heavy keys, and the share of keys
    that bucket sizes are estimated from (None: all keys). Estimates only decide
    how rows are dealt; positions and ranks count the parts, selections recount.
    """

    k: int = 256
    base_rows: int = 1 << 12
    parts: int | None = None
    depth: int | None = None
    equality: bool = True
    oversampling: float = sampling.OVERSAMPLING
    histogram_share: float | None = None
    seed: int = 42


@dataclass
class SortedFrame:
    """A physically sorted frame: parts in order, rows sorted within; ``offsets`` are the rows before each part.

    ``parted`` holds the same rows with their part before they move, for counts
    that need no shuffle of the payload.
    """

    df: DataFrame
    key: KeySpec
    parts: int
    offsets: np.ndarray | None
    model: Model | None
    packing: Packing | None
    sizes: Histogram | None
    trace: Trace = field(default_factory=Trace)
    parted: DataFrame | None = None

    def rows(self) -> DataFrame:
        """The rows in order, without the part."""
        return self.df.drop(PART)

    def counts(self) -> np.ndarray:
        """Rows before each part; counted where packing couldn't tell."""
        if self.offsets is None:
            found = np.zeros(self.parts, np.int64)
            for r in (self.parted if self.parted is not None else self.df).groupBy(PART).count().collect():
                found[r[PART]] = r["count"]
            self.offsets = np.cumsum(found) - found
        return self.offsets

    def exact_sizes(self, df: DataFrame) -> Histogram:
        """Bucket sizes of ``df``, counted now if they were estimated."""
        if not self.sizes.exact:
            counted = histogram(df, self.key.plain(), self.model)
            self.sizes = _in_output_order(counted, self.model, self.key)
        return self.sizes

    def select(self, *columns: str) -> SortedFrame:
        """Fewer columns, still in order."""
        return replace(self, df=self.df.select(PART, *dict.fromkeys([self.key.column, *self.key.ties, *columns])))

    def page(self, start: int, rows: int) -> DataFrame:
        """Rows ``start`` to ``start + rows`` of the order; parts outside are not sorted."""
        from modelsort.operators.rank import global_position

        before = self.counts()
        first = int(np.searchsorted(before, start, side="right")) - 1
        last = int(np.searchsorted(before, start + rows, side="left")) - 1
        near = replace(self, df=self.df.where(F.col(PART).between(max(first, 0), max(last, 0))))
        return global_position(near, mode="window").where((F.col("position") > start) & (F.col("position") <= start + rows))


def _statistics(df: DataFrame, key: KeySpec) -> tuple[int, int, float, float]:
    """Rows, rows with a finite key, and the range of those, in one key-only scan."""
    n, m, low, high = df.select(numeric(df, key).alias("x")).agg(*_measures()).first()
    return n, m, low, high


def _measures() -> list[Column]:
    finite = valid(F.col("x")) & (F.abs("x") < float("inf"))
    return [F.count("*"), F.count(F.when(finite, 1)), F.min(F.when(finite, F.col("x"))), F.max(F.when(finite, F.col("x")))]


def _observed_sample(df: DataFrame, key: KeySpec, config: SortConfig) -> tuple[int, int, float, float, np.ndarray]:
    """Statistics and training sample from one scan: the rows are counted first, which Parquet answers from its footers."""
    n = df.count()
    seen = Observation()
    names = ("n", "m", "low", "high")
    keys = df.select(numeric(df, key).alias("x")).observe(seen, *(e.alias(c) for e, c in zip(_measures(), names, strict=True)))
    sample = sampling.draw(keys, F.col("x"), sampling.sample_size(max(n, 2), config.k, config.oversampling), n, config.seed)
    got = seen.get
    return (*(got[c] for c in names), sample)


def finish(df: DataFrame, key: KeySpec, model: Model, sizes: Histogram, parts: int, trace: Trace, raw: KeySpec | None = None, seed: int = 42, local: Callable[[DataFrame, list[int]], DataFrame] | None = None) -> SortedFrame:
    """Pack the buckets, move the payload once, and sort within parts, by ``raw`` if the key is coded.

    A bucket that would fill a part one and a half times is cut by raw keys and
    ties first, in a scan of these columns. ``local`` sorts the rows of a part in
    place of Spark, given the moved rows with their bucket and the buckets that need no sort.
    """
    order, rows, alike = raw or key, sizes.rows, np.zeros(len(sizes.rows), bool)
    target = max(1.0, sizes.n / max(parts, 1))
    large = np.flatnonzero(rows >= max(1.5 * target, CUT_ROWS)) if parts > 1 else np.zeros(0, np.int64)
    assigned = assign(df, key, model)
    exact = sizes.exact
    if len(large) and all(isinstance(df.schema[c].dataType, T.AtomicType) for c in order.columns()):
        # Only what decides the order is read.
        # A partition number has no sign bit, so nothing is added; but filters on the bucket stay above the model,
        # which would otherwise be written out in each of them, with the view of a text wherever it reads one.
        zero = F.shiftright(F.spark_partition_id(), 31)
        keys = assign(df.select(*dict.fromkeys([key.column, *order.columns()])), key, model).withColumn(BUCKET, F.col(BUCKET) + zero)
        cuts = find_cuts(keys, order, {int(b): int(rows[b]) for b in large}, target, seed)
        first = cuts.first(len(rows))
        fine = np.zeros(len(rows) + len(cuts.rows), np.int64)
        fine[first] = np.where(np.isin(np.arange(len(rows)), large), 0, rows)
        alike = np.zeros(len(fine), bool)
        for b, n, same in count_pieces(keys, cuts, large.tolist()):
            fine[b], alike[b] = n, same
        rows, assigned = fine, cuts.attach(assigned)
    packing = pack(rows, parts, alike, target)
    copies = False
    if (packing.spread > 1).any():
        parted, per_part, copies = spread_parts(assigned, packing, rows, target, order.columns())
    else:
        parted = assigned.withColumn(PART, part_column(packing))
        parted = parted if local else parted.drop(BUCKET)
        per_part = np.bincount(packing.part, weights=rows, minlength=packing.parts).astype(np.int64)
    moved = move(parted, packing.parts)
    if local and not copies and BUCKET in parted.columns:
        moved = local(moved, np.flatnonzero(alike).tolist())
        parted = parted.drop(BUCKET)
    else:
        moved = moved.sortWithinPartitions(*order.order())
    if copies:
        lay_out = F.explode(F.array_repeat(F.lit(0), F.col("__copies")))
        moved, parted = (f.withColumn("__copy", lay_out).drop("__copies", "__copy") for f in (moved, parted))
    return SortedFrame(moved, order, packing.parts, np.cumsum(per_part) - per_part if exact else None, model, packing, sizes, trace, parted)


def partition_sort(df: DataFrame, key: KeySpec | str, fit: Callable[[np.ndarray, int], Model], config: SortConfig = SortConfig()) -> SortedFrame:
    """Sample, fit, count, refine, cut, pack, move once, sort within parts.

    Nulls go to the end the key asks for, NaN above all numbers, -0.0 equals 0.0
    and infinities are ordinary keys. An empty table gives an empty frame. A
    key that holds most rows spans as many parts as these fill: by its ties, or
    freely if it has none.
    """
    key = with_prefix(df, as_key(key))
    parts = config.parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    view, shown = _view(df, key)
    n, m, low, high, sample = _observed_sample(view, shown, config)
    if not m or low == high or not len(sample):
        model: Model = LinearBucket.constant(1)
    else:
        heavy = sampling.heavy_keys(sample, config.k) if config.equality else np.zeros(0)
        light = sample[~np.isin(sample, heavy)]
        model = fit(light if len(light) else sample, config.k)
        if len(heavy) and not isinstance(model, SplitterTree):
            model = WithHeavy(model, heavy)
    limit = max(config.base_rows, n // max(2 * parts, 1))
    model, sizes, trace = refine(view, shown, model, fit, config.k, limit, config.depth, config.histogram_share, config.seed)
    return finish(df, key, model, _in_output_order(sizes, model, key), parts, trace, seed=config.seed)


def _view(df: DataFrame, key: KeySpec) -> tuple[DataFrame, KeySpec]:
    """What models are fitted on: the column itself, or the numbers of strings, written once, since texts may be long and are scanned twice a round."""
    if not isinstance(df.schema[key.column].dataType, (T.StringType, T.BinaryType)):
        return df, key
    return materialize(df.select(numeric(df, key).alias("x")), "key-view"), KeySpec("x", key.ascending, key.nulls_first)


def _in_output_order(sizes: Histogram, model: Model, key: KeySpec) -> Histogram:
    """A histogram of ascending buckets with nulls first, as the key's own order has it."""
    b = model.buckets
    order = np.arange(b + 3)
    middle = order[1 : b + 2] if key.ascending else order[1 : b + 2][::-1]
    place = np.concatenate([[0], middle, [b + 2]]) if key.nulls_first else np.concatenate([[b + 2], middle, [0]])
    return Histogram(sizes.rows[place], sizes.low[place], sizes.high[place], sizes.exact)


def linear_partition_sort(df: DataFrame, key: KeySpec | str, *, fit: str = "min_conflict", config: SortConfig = SortConfig()) -> SortedFrame:
    """The proposed sorter: one bounded line per step, trained by minimum conflict (or ``lsq``, ``minmax``, ``balanced``)."""
    return partition_sort(df, key, FITS[fit], config)


def tree_sample_sort(df: DataFrame, key: KeySpec | str, *, mode: str = "heap", equality: bool = True, config: SortConfig = SortConfig()) -> SortedFrame:
    """k-way sample sort by a splitter tree with equality buckets."""
    return partition_sort(df, key, lambda s, k: SplitterTree.fit(s, k, equality, mode), replace(config, equality=False))


def two_way_sort(df: DataFrame, key: KeySpec | str, *, config: SortConfig = SortConfig()) -> SortedFrame:
    """Quicksort's partitioning: one pivot a step."""
    return partition_sort(df, key, lambda s, k: SplitterTree.fit(s, 2, False, "case"), replace(config, k=2, equality=False))


def quantile_sort(df: DataFrame, key: KeySpec | str, *, config: SortConfig = SortConfig()) -> SortedFrame:
    """Splitters from the built-in quantile sketch; a baseline without a sample."""
    key = with_prefix(df, as_key(key))
    x = numeric(df, key)
    model = SplitterTree.from_sketch(df.where(valid(x)), x, config.k)
    return sort_with(df, key, model, config)


def radix_partition_sort(df: DataFrame, key: KeySpec | str, *, bits: int = 8, extract: bool = True, config: SortConfig = SortConfig()) -> SortedFrame:
    """Most-significant digits of the key, or of its order-preserving bits if ``extract``."""
    key = with_prefix(df, as_key(key))
    n, m, low, high = _statistics(df, key)
    if not m or low == high:
        return sort_with(df, key, LinearBucket.constant(1), config)
    fit = lambda s, k: RadixBucket.fit(s[0], s[-1], bits)
    if extract and dict(df.dtypes)[key.column] in ("double", "float"):
        # NaN keeps a slot of its own, so only what a model places is coded; the range is coded on the driver.
        x = numeric(df, key)
        # Nothing is added by the sign of a partition number, but the bits are then worked out once, not wherever they are used.
        zero = F.shiftright(F.spark_partition_id(), 31)
        coded = df.withColumn("__bits", F.when(valid(x), order_bits(x).cast("double")).otherwise(x) + zero)
        ends = order_bits_np(np.array([low, high])).astype(float)
        code = KeySpec("__bits", key.ascending, key.nulls_first)
        result = sort_with(coded, code, RadixBucket.fit(*ends, bits), config, fit, key)
        return replace(result, df=result.df.drop("__bits"), parted=result.parted.drop("__bits"), model=None)  # the model reads coded keys only
    return sort_with(df, key, RadixBucket.fit(low, high, bits), config, fit)


def sort_with(df: DataFrame, key: KeySpec | str, model: Model, config: SortConfig = SortConfig(), fit: Callable[[np.ndarray, int], Model] = LinearBucket.fit_min_conflict, raw: KeySpec | None = None) -> SortedFrame:
    """Sort by a model that is already there, as for appended data; large buckets are refined by ``fit``.

    ``raw`` is the key to sort by within parts if ``key`` is only a coded form of it.
    """
    key = as_key(key)
    parts = config.parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    first = histogram(df, key.plain(), model, config.histogram_share, config.seed)
    limit = max(config.base_rows, first.n // max(2 * parts, 1))
    model, sizes, trace = refine(df, key, model, fit, config.k, limit, config.depth, config.histogram_share, config.seed)
    return finish(df, key, model, _in_output_order(sizes, model, key), parts, trace, raw, config.seed)


def classic_copy_sort(df: DataFrame, key: KeySpec | str, *, config: SortConfig = SortConfig()) -> SortedFrame:
    """Out-of-place sample sort: a bucketed copy of all rows is written before they are sorted."""
    sorted_ = tree_sample_sort(df, key, config=config)
    copy = materialize(move(sorted_.parted, sorted_.parts), "bucketed-copy")
    return replace(sorted_, df=move(copy, sorted_.parts).sortWithinPartitions(*sorted_.key.order()), parted=copy)


def builtin_sort(df: DataFrame, key: KeySpec | str, *, sequential: bool = False) -> DataFrame:
    """Spark's own sort: range exchange, or one task."""
    order = as_key(key).order()
    return df.coalesce(1).sortWithinPartitions(*order) if sequential else df.orderBy(*order)


def ideal_place(df: DataFrame, key: str) -> DataFrame:
    """One-pass ideal sort of distinct keys: every row's place is its exact distribution value."""
    from modelsort.operators.rank import exact_ecdf

    return exact_ecdf(df, key).drop("ecdf")


def ecdf_model(sample: np.ndarray, leaves: int = 128) -> Rmi:
    return Rmi.two_level(sample, max(1, min(leaves, len(sample) // 4 or 1))).monotone(sample)


def ecdf_two_pass_sort(df: DataFrame, key: KeySpec | str, *, k1: int = 32, k2: int = 32, fraction: float = 0.01, leaves: int = 128, config: SortConfig = SortConfig()) -> SortedFrame:
    """Two partitioning rounds by one eCDF of a 1 % sample, then model-based counting sort and correction in each bucket.

    A round of ``k1`` buckets and one of ``k2`` within each by the same eCDF give
    one number, so both are one move. Buckets whose rows are alike are left as they
    are; the others are taken one at a time (``counting_order``). The model is
    made monotone before the move, since no correction within a part reaches
    across parts. Where the numeric view rounds the raw key (strings, huge
    integers, decimals), Spark's local sort is the base case.
    """
    key = with_prefix(df, as_key(key))
    parts = config.parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    n, m, low, high = _statistics(df, key)
    finite = df.select(numeric(df, key).alias("x")).where(valid(F.col("x")) & (F.abs("x") < float("inf")))
    rmi = None
    if m and low < high:
        few = fraction * m < 1024  # a share of a small table is no sample; it is taken whole
        rmi = Rmi.two_level_distributed(finite if few else finite.sample(fraction, config.seed), "x", leaves)
    model: Model = EcdfBucket(rmi, k1 * k2) if rmi else LinearBucket.constant(1)
    sizes = histogram(df, key.plain(), model, None, config.seed)
    kind = df.schema[key.column].dataType
    exact = isinstance(kind, (T.DoubleType, T.FloatType, T.DateType)) or (isinstance(kind, T.IntegralType) and m and max(abs(low), abs(high)) <= 2.0**53)
    plain = all(isinstance(df.schema[t].dataType, T.AtomicType) for t in key.ties)
    local = (lambda moved, alike: base_cases(moved, key, rmi, k1 * k2, alike)) if rmi and exact and plain else None
    return finish(df, key, model, _in_output_order(sizes, model, key), parts, Trace([int(sizes.rows.max(initial=0))]), seed=config.seed, local=local)


def counting_order(x: np.ndarray, predicted: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Order of keys by predicted place, and the runs in which they are not in place yet.

    The places are counted, summed up and filled in order of arrival. A run ends
    where every key before is less than every key after; returned are the order,
    the run of each position, and whether the run holds more than one row. Only
    rows of such runs have to be looked at by the correction.
    """
    n = len(x)
    slot = np.clip(predicted, 0, max(n - 1, 0))
    order = np.argsort(slot, kind="stable")
    there = x[order]
    high, low = np.maximum.accumulate(there), np.minimum.accumulate(there[::-1])[::-1]
    run = np.concatenate([[0], np.cumsum(high[:-1] < low[1:])]) if n else np.zeros(0, np.int64)
    return order, run, (np.bincount(run)[run] > 1) if n else np.zeros(0, bool)


def corrected(table: pa.Table, x: np.ndarray, predicted: np.ndarray, key: KeySpec) -> tuple[np.ndarray, np.ndarray]:
    """Final order of a bucket's rows, and each row's place by prediction alone.

    Correction touches the open runs only and sorts each by raw key and ties.
    """
    order, run, open_ = counting_order(x, predicted)
    slot = np.empty(len(x), np.int64)
    slot[order] = np.arange(len(x))
    at = np.flatnonzero(open_)
    if len(at):
        rows = table.select(key.columns()).take(pa.array(order[at]))
        names, columns = [("run", "ascending")], [pa.array(run[at])]
        for i, (name, up) in enumerate([(key.column, key.ascending), *((t, True) for t in key.ties)]):
            column = rows.column(name)
            if pa.types.is_floating(column.type):
                mask = pc.is_null(column).to_numpy()
                column = pa.array(order_bits_np(column.fill_null(0.0).to_numpy().astype(float)), mask=mask)
            names.append((f"c{i}", "ascending" if up else "descending"))
            columns.append(column)
        by = pc.sort_indices(pa.table(columns, [c for c, _ in names]), sort_keys=names, null_placement="at_start").to_numpy()
        order[at] = order[at][by]
    return order, slot


def base_cases(moved: DataFrame, key: KeySpec, rmi: Rmi, buckets: int, alike: list[int]) -> DataFrame:
    """Rows of each part in order, a bucket at a time; rows of the buckets ``alike`` pass as they come.

    Spark's local sort by bucket brings a bucket's rows together. Memory is that
    of one bucket, which cuts keep near a part's share.
    """
    schema = T.StructType([f for f in moved.schema.fields if f.name != BUCKET])
    same = np.array(sorted(alike), np.int64)
    sign = 1.0 if key.ascending else -1.0

    def order_of(table: pa.Table) -> pa.Table:
        column = table.column(key.column)
        if column.null_count or (pa.types.is_floating(column.type) and pc.any(pc.is_nan(column)).as_py()):
            x, predicted = np.zeros(len(table)), np.zeros(len(table), np.int64)
        else:
            column = column.cast(pa.int32()) if pa.types.is_date32(column.type) else column
            x = column.to_numpy().astype(float)
            share = rmi.predict(x) * buckets
            within = share - np.floor(share.min()) if len(share) else share
            spread = max(1.0, np.ceil(within.max(initial=0.0)))
            within = within / spread if key.ascending else 1 - within / spread
            x, predicted = sign * x, np.floor(within * len(x)).astype(np.int64)
        return table.take(pa.array(corrected(table, x, predicted, key)[0]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        now = None
        for batch in batches:
            ids = batch.column(BUCKET).to_numpy()
            edges = np.concatenate([[0], np.flatnonzero(np.diff(ids)) + 1, [len(ids)]]) if len(ids) else np.zeros(1, int)
            rest = batch.drop_columns([BUCKET])
            for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
                if held and ids[a] != now:
                    yield from order_of(pa.Table.from_batches(held)).combine_chunks().to_batches()
                    held = []
                now, piece = ids[a], rest.slice(a, b - a)
                if now in same:
                    yield piece
                else:
                    held.append(piece)
        if held:
            yield from order_of(pa.Table.from_batches(held)).combine_chunks().to_batches()

    return moved.sortWithinPartitions(BUCKET).mapInArrow(run, schema)


def counting_sort(df: DataFrame, key: KeySpec | str, rmi: Rmi) -> DataFrame:
    """The eCDF sorter's base case on each partition as one bucket, with what it did.

    Adds ``slot``, the place by prediction, and ``place``, the place by key; where
    they differ the correction moved the row. Keys must be numbers without null and NaN.
    """
    key = as_key(key)
    schema = T.StructType([*df.schema.fields, T.StructField("slot", T.LongType()), T.StructField("place", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = list(batches)
        if not parts:
            return
        table = pa.Table.from_batches(parts)
        x = table.column(key.column).to_numpy().astype(float)
        order, slot = corrected(table, x, np.floor(rmi.predict(x) * len(x)).astype(np.int64), key)
        out = table.take(pa.array(order)).append_column("slot", pa.array(slot[order])).append_column("place", pa.array(np.arange(len(x))))
        yield from out.combine_chunks().to_batches()

    return df.mapInArrow(run, schema)


def small_radix_order(values: np.ndarray, bits: int = 8) -> np.ndarray:
    """Base case for small inputs: order by least-significant digits of the order-preserving bits."""
    values = np.asarray(values)
    coded = order_bits_np(values.astype(float)) if values.dtype.kind == "f" else values.astype(np.int64)
    codes = coded.view(np.uint64) ^ np.uint64(1 << 63)
    order = np.arange(len(codes))
    differs = int(np.bitwise_or.reduce(codes ^ codes[0])) if len(codes) else 0
    for shift in range(0, 64, bits):
        if differs >> shift & ((1 << bits) - 1):
            digit = ((codes[order] >> np.uint64(shift)) & np.uint64((1 << bits) - 1)).astype(np.uint16)
            order = order[np.argsort(digit, kind="stable")]
    return order


def small_radix_sort(values: np.ndarray, bits: int = 8) -> np.ndarray:
    return np.asarray(values)[small_radix_order(values, bits)]


#: Fits of the sequential sorters by name; the library's has none.
SEQUENTIAL: dict[str, Callable[[np.ndarray, int], Model] | None] = {
    "linear": LinearBucket.fit_min_conflict,
    "tree": lambda s, k: SplitterTree.fit(s, k, True),
    "radix": lambda s, k: RadixBucket.fit(s[0], s[-1], 8),
    "ecdf": lambda s, k: EcdfBucket(ecdf_model(s), 4 * k),
    "library": None,
}


def sequential_order(x: np.ndarray, method: str = "linear", k: int = 256, base: int = 1 << 12) -> np.ndarray:
    """Order of keys by a sequential sorter: partitioning by its model until buckets fit the radix base case.

    Neighbouring buckets that fit the base case together share one. Radix reads
    its digits off the order-preserving bits. The eCDF sorter takes a 1 % sample,
    two rounds, and counting sort with correction as its base case.
    """
    fit = SEQUENTIAL[method]
    if fit is None:
        return np.argsort(x, kind="stable")
    finite = x[np.isfinite(x)]
    ends = (finite.min(), finite.max()) if len(finite) else (0.0, 0.0)
    # Infinities go where the nearest finite key goes; base cases read the raw keys.
    coded = order_bits_np(x).astype(float) if method == "radix" else np.clip(x, *ends)

    def finish_(at: np.ndarray) -> np.ndarray:
        return at[small_radix_order(x[at])]

    def counted(at: np.ndarray, model: Model) -> np.ndarray:
        share = model.ecdf.predict(coded[at]) * model.k
        order, run, open_ = counting_order(x[at], np.floor((share - np.floor(share.min())) * len(at)).astype(np.int64))
        dirty = np.flatnonzero(open_)
        order[dirty] = order[dirty][np.lexsort((x[at][order[dirty]], run[dirty]))]
        return at[order]

    def split(at: np.ndarray, depth: int) -> list[np.ndarray]:
        own = coded[at]
        if own.min() == own.max():
            return [at if x[at].min() == x[at].max() else finish_(at)]
        if len(at) <= base and depth:
            return [finish_(at)]
        size = max(1024, len(at) // 100) if method == "ecdf" else sampling.sample_size(len(at), k)
        picked = np.random.default_rng(len(at)).choice(own, min(len(at), size), replace=False)
        sample = np.sort(np.append(picked, [own.min(), own.max()]) if method == "radix" else picked)
        model = fit(sample, k)
        bucket = model.predict(own)
        if bucket.min() == bucket.max():
            return [finish_(at)]
        by = np.argsort(bucket.astype(np.uint16) if model.buckets <= 1 << 16 else bucket, kind="stable")  # digits of 16 bits are sorted by counting
        cuts = np.searchsorted(bucket[by], np.arange(model.buckets + 1))
        pieces = [at[by[a:b]] for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True) if b > a]
        if method == "ecdf":
            return [p if x[p].min() == x[p].max() else counted(p, model) for p in pieces]
        out: list[np.ndarray] = []
        near: list[np.ndarray] = []
        for piece in [*pieces, None]:
            if near and (piece is None or sum(map(len, near)) + len(piece) > base):
                out, near = [*out, finish_(np.concatenate(near))], []
            if piece is not None and len(piece) <= base:
                near.append(piece)
            elif piece is not None:
                out += split(piece, depth + 1)
        return out

    return np.concatenate(split(np.arange(len(x)), 0)) if len(x) else np.zeros(0, np.int64)


#: Rows and bytes that a sequential sort holds at once; more are dealt to a file of its task first.
HELD_ROWS, HELD_BYTES = 1 << 20, 1 << 25


def _held(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The rows in tables that a sequential sort may hold."""
    held: list[pa.RecordBatch] = []
    rows = size = 0
    for batch in batches:
        if held and (rows + batch.num_rows > HELD_ROWS or size + batch.nbytes > HELD_BYTES):
            yield pa.Table.from_batches(held)
            held, rows, size = [], 0, 0
        held.append(batch)
        rows, size = rows + batch.num_rows, size + batch.nbytes
    if held:
        yield pa.Table.from_batches(held)


def _digits_between(low: float, high: float) -> Callable[[np.ndarray], np.ndarray]:
    """The leading eight bits in which the order-preserving bits from ``low`` to ``high`` differ; it tells any two ends apart."""
    first, last = (int(v) for v in order_bits_np(np.array([low, high])))
    shift = np.uint64(max(0, (last - first).bit_length() - 8))
    base = np.uint64(first & ((1 << 64) - 1))
    return lambda x: np.minimum((order_bits_np(x).view(np.uint64) - base) >> shift, np.uint64(255)).astype(np.uint16)


def _dealer(x: np.ndarray, method: str, k: int, ends: tuple[float, float] | None) -> Callable[[np.ndarray], np.ndarray]:
    """A sorter's own partitioning, fitted on a sample of ``x``; splitters stand for the library's sort, which has no model.

    Where it would leave rows with the keys ``ends`` together, digits of their bits take over.
    """
    finite = x[np.isfinite(x)]
    low, high = ends or (-np.inf, np.inf)
    if not len(finite):
        return _digits_between(low, high)
    bounds = (finite.min(), finite.max())
    if ends:
        bounds = (low if np.isfinite(low) else bounds[0], high if np.isfinite(high) else bounds[1])
    coded = (lambda v: order_bits_np(v).astype(float)) if method == "radix" else (lambda v: np.clip(v, *bounds))
    size = max(1024, len(finite) // 100) if method == "ecdf" else sampling.sample_size(len(finite), k)
    picked = np.random.default_rng(len(x)).choice(finite, min(len(finite), size), replace=False)
    model = (SEQUENTIAL[method] or SEQUENTIAL["tree"])(np.sort(coded(np.append(picked, bounds))), k)
    if model.buckets > 1 << 16 or (ends and len(set(model.predict(coded(np.array(ends))).tolist())) == 1):
        return _digits_between(low, high)
    return lambda v: model.predict(coded(v)).astype(np.uint16)


def _dealt(tables: Iterable[pa.Table], key: str, method: str, k: int, ends: tuple[float, float] | None = None, depth: int = 0) -> Iterator[tuple[pa.Table, bool]]:
    """Rows by bucket in the order of the key, through a compressed file; buckets of several keys that are too large to hold are dealt again."""
    places: dict[int, list[tuple[int, int]]] = {}
    found: dict[int, tuple[float, float, int, int]] = {}  # least and largest key, rows, bytes
    deal = None
    with tempfile.TemporaryFile() as file:
        for table in tables:
            x = table.column(key).to_numpy().astype(float)
            if deal is None:
                # A model whose buckets hardly shrink gives way; digits of the bits end in eight rounds.
                deal = _dealer(x, method, k, ends) if depth < 3 else _digits_between(*ends)
            bucket = deal(x)
            by = np.argsort(bucket, kind="stable")
            table, x, bucket = table.take(pa.array(by)), x[by], bucket[by]
            starts = np.concatenate([[0], np.flatnonzero(np.diff(bucket)) + 1])
            lows, highs = np.minimum.reduceat(x, starts), np.maximum.reduceat(x, starts)
            for b, a, e, low, high in zip(bucket[starts].tolist(), starts.tolist(), [*starts[1:].tolist(), len(x)], lows.tolist(), highs.tolist(), strict=True):
                piece = table.slice(a, e - a)
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as writer:
                    writer.write_table(piece)
                places.setdefault(b, []).append((file.tell(), file.write(sink.getvalue())))
                before = found.get(b, (low, high, 0, 0))
                found[b] = (min(before[0], low), max(before[1], high), before[2] + e - a, before[3] + piece.nbytes)

        def blocks(b: int) -> Iterator[pa.RecordBatch]:
            for at, size in places[b]:
                file.seek(at)
                yield from pa.ipc.open_stream(file.read(size)).read_all().to_batches()

        for b in sorted(found):
            low, high, rows, size = found[b]
            if low == high:
                yield from ((table, True) for table in _held(blocks(b)))
            elif rows <= HELD_ROWS and size <= HELD_BYTES:
                yield pa.Table.from_batches(blocks(b)), False
            else:
                yield from _dealt(_held(blocks(b)), key, method, k, (low, high), depth + 1)


def in_pieces(batches: Iterable[pa.RecordBatch], key: str, method: str, k: int = 256) -> Iterator[tuple[pa.Table, bool]]:
    """Tables in the order of a key, each no more than a sequential sort holds, and whether all keys of one are alike."""
    tables = _held(batches)
    begin = list(itertools.islice(tables, 2))
    if len(begin) < 2:
        yield from ((table, False) for table in begin)
    else:
        yield from _dealt(itertools.chain(begin, tables), key, method, k)


def sequential_sort(df: DataFrame, key: str, method: str = "linear", k: int = 256, base: int = 1 << 12) -> DataFrame:
    """Sequential form of a sorter (``linear, tree, radix, ecdf, library``) in one task.

    Memory is that of ``HELD_ROWS`` rows, however many there are: the sorter's own
    model deals more to a file first, which the task deletes. ``key`` must be a
    number without null and NaN. Adds ``position`` from 1.
    """
    schema = T.StructType([*df.schema.fields, T.StructField("position", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = 1
        for table, alike in in_pieces(batches, key, method, k):
            if not alike:
                x = table.column(key).to_numpy().astype(float)
                table = table.take(pa.array(sequential_order(x, method, k, base)))
            out = table.append_column("position", pa.array(np.arange(place, place + len(table))))
            place += len(table)
            yield from out.combine_chunks().to_batches(max_chunksize=1 << 16)

    return df.coalesce(1).mapInArrow(run, schema)


def auto_sort(df: DataFrame, key: KeySpec | str, config: SortConfig = SortConfig()) -> SortedFrame:
    """Pick the model by what a sample shows: few rows one part, many duplicates a tree, else the line."""
    key = with_prefix(df, as_key(key))
    n, m, low, high = _statistics(df, key)
    if n <= config.base_rows:
        return linear_partition_sort(df, key, config=replace(config, parts=1))
    sample = sampling.draw(df, numeric(df, key), sampling.sample_size(max(m, 2), config.k), max(m, 1), config.seed) if m else np.zeros(0)
    duplicates = 1 - len(np.unique(sample)) / max(len(sample), 1)
    return tree_sample_sort(df, key, config=config) if duplicates > 0.5 else linear_partition_sort(df, key, config=config)


def merge_runs(runs: list[SortedFrame], config: SortConfig = SortConfig()) -> SortedFrame:
    """One sorted frame from several, by the first run's model."""
    first = runs[0]
    every = first.rows()
    for run in runs[1:]:
        every = every.unionByName(run.rows())
    return sort_with(every, first.key, first.model, config)


def sorted_by(column: str, method: str = "linear", **options) -> Callable[[DataFrame], DataFrame]:
    """For ``DataFrame.transform``: rows in the order of a column."""
    sorter = {"linear": linear_partition_sort, "tree": tree_sample_sort, "radix": radix_partition_sort, "ecdf": ecdf_two_pass_sort, "auto": auto_sort}[method]
    return lambda df: sorter(df, KeySpec(column), **options).rows()

