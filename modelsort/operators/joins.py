"""Joins on sorted, bucketed keys: merge, band, interval, as-of, and their baselines."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from modelsort.functions import sampling
from modelsort.functions.keys import KeySpec, as_key, numeric, slotted, valid, with_prefix
from modelsort.functions.models import LinearBucket
from modelsort.operators.sorters import CUT_ROWS
from modelsort.plans.partitioner import BUCKET, PART, assign, histogram, holds_map, pack, scatter

#: Rows of a cell of the ordered key in band, interval, theta and as-of joins.
CELL_ROWS = 500_000
HOW = ("inner", "left", "right", "full", "left_semi", "left_anti")


def fit_line(df: DataFrame, key: KeySpec | str, k: int = 256, seed: int = 42) -> LinearBucket:
    """A least-conflict line of one key column."""
    key = as_key(key)
    x = numeric(df, key)
    n = df.select(key.column).where(F.col(key.column).isNotNull()).count()
    return LinearBucket.fit_min_conflict(sampling.draw(df, x, sampling.sample_size(max(n, 2), k), max(n, 1), seed), k)


def merge(left: DataFrame, right: DataFrame, on: str, how: str = "inner", k: int = 256, parts: int | None = None) -> DataFrame:
    """Equi-join of two frames that one model deals to the same parts; no other shuffle is planned.

    A bucket that would fill a part twice is looked into: keys that hold that
    much of a side are joined apart, dealt by salt (``salted``). Semi and anti
    joins take each key of the right side once.
    """
    parts = parts or int(left.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if how in ("left_semi", "left_anti"):
        right = right.select(on).distinct()
    key = with_prefix(left, KeySpec(on))
    model = fit_line(left, key, k)
    a, b = histogram(left, key, model).rows, histogram(right, key, model).rows
    target = max(1.0, (a + b).sum() / parts)
    large = np.flatnonzero(np.maximum(a, b) >= max(2 * target, CUT_ROWS))
    heavy: tuple[list, list] = ([], [])
    if len(large):
        heavy = tuple(_heavy_keys(assign(side.select(on), key, model).where(F.col(BUCKET).isin(large.tolist())), on, target) for side in (left, right))
    special = [*heavy[0], *heavy[1]]
    usual = ~F.coalesce(F.col(on).isin(special), F.lit(False)) if special else F.lit(True)
    packing = pack(a + b, parts)
    c, d = scatter(assign(left.where(usual), key, model), packing), scatter(assign(right.where(usual), key, model), packing)
    joined = c.hint("merge").join(d, [PART, on], how).drop(PART)
    for keys, swap in ((heavy[0], False), ([v for v in heavy[1] if v not in set(heavy[0])], True)):
        if keys:
            joined = joined.unionByName(_salt_join(left.where(F.col(on).isin(keys)), right.where(F.col(on).isin(keys)), on, how, max(2, int(min(parts, 2 * (a + b).max() / target))), swap))
    return joined


def _heavy_keys(rows: DataFrame, on: str, more_than: float) -> list:
    """Keys with more rows than that; there are at most rows / more_than of them."""
    return [r[0] for r in rows.where(F.col(on).isNotNull()).groupBy(on).count().where(F.col("count") > more_than).collect()]


def _salt_join(left: DataFrame, right: DataFrame, on: str, how: str, salts: int, swap: bool = False) -> DataFrame:
    """Join of rows with keys that are heavy on the left (on the right if ``swap``), dealt over ``salts`` tasks.

    The other side's rows are repeated for each salt. They all have a partner, since
    their key is heavy there, so a repeated row is never an unmatched one, and outer
    joins keep unmatched rows of the heavy side only. Salts come from the row's hash
    and its task, which a repeated task gives again.
    """
    many, few = (right, left) if swap else (left, right)
    hashed = [c for c in many.columns if not holds_map(many.schema[c].dataType)]
    a = many.withColumn("__salt", F.pmod(F.xxhash64(*hashed) + F.spark_partition_id(), F.lit(salts)).cast("int"))
    b = few.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    if how in ("left_semi", "left_anti"):
        if swap:
            return few.join(many.select(on).distinct(), on, how)
        return a.join(b, [on, "__salt"], how).drop("__salt")
    outer = how in (("right", "full") if swap else ("left", "full"))
    joined = a.join(b, [on, "__salt"], "left" if outer else "inner").drop("__salt")
    return joined.select(on, *(c for c in left.columns if c != on), *(c for c in right.columns if c != on))


def salted(left: DataFrame, right: DataFrame, on: str, how: str = "inner", heavy_share: float = 0.01, salts: int = 16) -> DataFrame:
    """Equi-join whose heavy left keys are spread over ``salts`` tasks, their right rows repeated for each.

    A key is heavy if it holds more than ``heavy_share`` of the left rows, so there are at most its inverse of them.
    """
    heavy = _heavy_keys(left, on, heavy_share * left.count())
    if not heavy:
        return left.join(right, on, how)
    is_heavy = F.coalesce(F.col(on).isin(heavy), F.lit(False))
    return left.where(~is_heavy).join(right.where(~is_heavy), on, how).unionByName(_salt_join(left.where(is_heavy), right.where(is_heavy), on, how, salts))


def hashed(left: DataFrame, right: DataFrame, on: str, how: str = "inner", broadcast_rows: int = 100_000) -> DataFrame:
    """Hash join: the right side is broadcast if it is counted small, else both are shuffled."""
    small = right.limit(broadcast_rows + 1).count() <= broadcast_rows and how not in ("right", "full")
    return left.join(F.broadcast(right) if small else right.hint("shuffle_hash"), on, how)


def semi(left: DataFrame, right: DataFrame, on: str, **options) -> DataFrame:
    return merge(left, right.select(on), on, "left_semi", **options)


def anti(left: DataFrame, right: DataFrame, on: str, **options) -> DataFrame:
    return merge(left, right.select(on), on, "left_anti", **options)


def _grid(left: DataFrame, key: str, cells: int | None) -> LinearBucket:
    """A line whose cells grow with the rows: about ``CELL_ROWS`` each, and four or more for every part."""
    n = left.select(key).count()
    cells = cells or max(256, 4 * int(left.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-n // CELL_ROWS))
    sample = sampling.draw(left, numeric(left, key), sampling.sample_size(max(n, 2), cells), max(n, 1))
    return LinearBucket.fit_min_conflict(sample, cells)


def band(left: DataFrame, right: DataFrame, left_key: str, right_key: str, delta: float, cells: int | None = None) -> DataFrame:
    """Pairs with |left - right| <= delta.

    Right rows visit every bucket that their band touches, left rows their own;
    equal buckets join, and the raw keys decide. Null and NaN keys have no pairs.
    """
    model = _grid(left, left_key, cells)
    x, y = numeric(left, left_key), numeric(right, right_key)
    a = left.where(valid(x)).withColumn(BUCKET, model.column(x))
    low, high = model.column(y - F.lit(float(delta))), model.column(y + F.lit(float(delta)))
    b = right.where(valid(y)).withColumn(BUCKET, F.explode(F.sequence(low, high)))
    near = F.abs(F.col(left_key).cast("double") - F.col(right_key).cast("double")) <= F.lit(float(delta))
    return a.join(b, BUCKET).where(near).drop(BUCKET)


def intervals(points: DataFrame, ranges: DataFrame, point: str, low: str, high: str, cells: int | None = None) -> DataFrame:
    """Points with every range [low, high] that holds them; ranges visit the buckets they cover."""
    model = _grid(points, point, cells)
    x = numeric(points, point)
    a = points.where(valid(x)).withColumn(BUCKET, model.column(x))
    lo, hi = numeric(ranges, low), numeric(ranges, high)
    b = ranges.where(valid(lo) & valid(hi) & (lo <= hi)).withColumn(BUCKET, F.explode(F.sequence(model.column(lo), model.column(hi))))
    return a.join(b, BUCKET).where(F.col(point).between(F.col(low), F.col(high))).drop(BUCKET)


def theta(left: DataFrame, right: DataFrame, left_key: str, right_key: str, op: str, cells: int | None = None) -> DataFrame:
    """Pairs under ``<, <=, >`` or ``>=``; buckets that can't hold pairs are never brought together.

    The result may be quadratic by nature; rows of the right side visit the buckets at or beyond their own.
    """
    model = _grid(left, left_key, cells)
    x, y = numeric(left, left_key), numeric(right, right_key)
    a = left.where(valid(x)).withColumn(BUCKET, model.column(x))
    own = model.column(y)
    reach = F.sequence(F.lit(0), own) if op in ("<", "<=") else F.sequence(own, F.lit(model.buckets - 1))
    b = right.where(valid(y)).withColumn(BUCKET, F.explode(reach))
    l, r = F.col(left_key), F.col(right_key)
    test = {"<": l < r, "<=": l <= r, ">": l > r, ">=": l >= r}[op]
    # A row is many by now, which Spark's estimate doesn't see: they are sorted, not broadcast from the driver.
    return a.join(b.hint("merge"), BUCKET).where(test).drop(BUCKET)


def asof(left: DataFrame, right: DataFrame, left_on: str, right_on: str, by: str | None = None, columns: tuple[str, ...] = (), direction: str = "backward", tolerance: float | None = None, cells: int | None = None) -> DataFrame:
    """Left rows with ``columns`` of the last right row at or before (or first at or after) them.

    Both sides are cut into the same buckets of the ordered key; a window runs
    within a bucket, and the state to begin with comes from the nearest earlier
    bucket that has right rows, one row per group and bucket. Ties on the right
    go by ``columns``. ``right_on`` is returned too; no match gives nulls.
    """
    x, y = numeric(left, left_on), numeric(right, right_on)
    model = _grid(left, left_on, cells)
    key = KeySpec(left_on)
    group = F.col(by) if by else F.lit(0)
    state = F.struct(y.alias("__y"), *(F.col(c) for c in dict.fromkeys((right_on, *columns))))
    back = direction == "backward"
    l = left.select(group.alias("__g"), x.alias("__t"), slotted(model.column(x), x, model.buckets, key).alias(BUCKET), F.lit(1 if back else 0).alias("__side"), F.struct(*left.columns).alias("__row"), F.lit(None).cast(right.select(state).schema[0].dataType).alias("__state"))
    r = right.where(valid(y)).select(group.alias("__g"), y.alias("__t"), slotted(model.column(y), y, model.buckets, key).alias(BUCKET), F.lit(0 if back else 1).alias("__side"), F.lit(None).cast(left.select(F.struct(*left.columns)).schema[0].dataType).alias("__row"), state.alias("__state"))
    pick = F.max if back else F.min
    edge = r.groupBy("__g", BUCKET).agg(pick("__state").alias("__edge"))
    along = Window.partitionBy("__g").orderBy(F.col(BUCKET) if back else F.desc(BUCKET)).rowsBetween(Window.unboundedPreceding, -1)
    buckets = l.select("__g", BUCKET).distinct().join(edge, ["__g", BUCKET], "full")
    carried = buckets.withColumn("__carry", F.last("__edge", ignorenulls=True).over(along)).select("__g", BUCKET, "__carry")
    order = [F.col("__t"), F.col("__side"), F.col("__state")] if back else [F.desc("__t"), F.desc("__side"), F.desc("__state")]
    within = Window.partitionBy("__g", BUCKET).orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = l.unionByName(r).withColumn("__seen", F.last("__state", ignorenulls=True).over(within)).where(F.col("__row").isNotNull())
    joined = seen.join(carried, ["__g", BUCKET], "left").withColumn("__m", F.coalesce("__seen", "__carry"))
    ok: Column = F.lit(True) if tolerance is None else F.abs(F.col("__t") - F.col("__m")["__y"]) <= F.lit(float(tolerance))
    given = F.when(ok & valid(F.col("__t")), F.col("__m"))
    return joined.withColumn("__m", given).select("__row.*", *(F.col("__m")[c].alias(c) for c in dict.fromkeys((right_on, *columns))))
