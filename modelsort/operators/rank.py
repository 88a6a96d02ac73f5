"""Positions and ranks of a sorted frame without a global window."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from modelsort.functions.keys import KeySpec
from modelsort.functions.literals import int_array
from modelsort.operators.sorters import SortedFrame, linear_partition_sort
from modelsort.plans.durable import materialize
from modelsort.plans.partitioner import PART, move

ROW_MASK = (1 << 33) - 1


def _before(values: list[int], part: Column) -> Column:
    return F.element_at(int_array(values), part + 1)


def global_position(sf: SortedFrame, name: str = "position", mode: str = "counter") -> DataFrame:
    """Rows with their place from 1: rows before the part plus a row counter, or a window per part."""
    offsets = sf.counts().tolist()
    if mode == "counter":
        place = _before(offsets, F.spark_partition_id()) + F.monotonically_increasing_id().bitwiseAND(F.lit(ROW_MASK)) + 1
    else:
        place = _before(offsets, F.col(PART)) + F.row_number().over(Window.partitionBy(PART).orderBy(*sf.key.order()))
    return sf.df.withColumn(name, place.cast("long")).drop(PART)


def lying_position(df: DataFrame, name: str = "position") -> DataFrame:
    """Rows with their place from 1 as they lie, for frames whose order is given by their partitions; rows are counted first."""
    part = F.spark_partition_id()
    found = {r["p"]: r["n"] for r in df.select(part.alias("p")).groupBy("p").agg(F.count("*").alias("n")).collect()}  # a row a partition
    before, total = [], 0
    for p in range(max(found, default=-1) + 1):
        before.append(total)
        total += found.get(p, 0)
    place = _before(before or [0], part) + F.monotonically_increasing_id().bitwiseAND(F.lit(ROW_MASK)) + 1
    return df.withColumn(name, place.cast("long"))


def _key_edges(sf: SortedFrame) -> list[dict]:
    """Rows, distinct keys, rows of the first and of the last key of each part that has rows, and whether a part begins with the key that ended the one before.

    Rows are counted by key before anything moves; the driver holds a row a part.
    """
    k = sf.key.column
    by_key = sf.parted.groupBy(PART, F.col(k).alias(k)).agg(F.count("*").alias("n"))
    here = Window.partitionBy(PART)
    placed = by_key.withColumn("i", F.row_number().over(here.orderBy(sf.key.order()[0]))).withColumn("d", F.count("*").over(here))
    ends = [F.max(F.when(F.col("i") == at, F.struct(F.col(k).alias("k"), "n"))).alias(name) for name, at in (("first", F.lit(1)), ("last", F.col("d")))]
    parts = placed.groupBy(PART).agg(F.sum("n").alias("n"), F.count("*").alias("d"), *ends)
    joined = F.coalesce(F.lag(F.struct(F.col("last")["k"])).over(Window.orderBy(PART)).eqNullSafe(F.struct(F.col("first")["k"])), F.lit(False))
    rows = parts.select(PART, "n", "d", F.col("first")["n"].alias("n_first"), F.col("last")["n"].alias("n_last"), joined.alias("joined")).collect()
    return [r.asDict() for r in sorted(rows, key=lambda r: r[PART])]


def ranks(sf: SortedFrame) -> DataFrame:
    """Rows with ``rank, dense_rank, percent_rank, cume_dist`` of the key, from windows within parts.

    A key that spans parts has the same numbers in all of them. The payload moves
    once and is sorted once, by the windows.
    """
    edges = _key_edges(sf)
    before, total, first_rank, last_rank, dense, dense_last = 0, sum(e["n"] for e in edges), 1, 1, 0, 0
    base, rank_first, dense_before, up_to_last, held = ([0] * sf.parts for _ in range(5))
    for e in edges:
        p = e[PART]
        first_rank = last_rank if e["joined"] else before + 1
        dense = dense_last if e["joined"] else dense_last + 1
        base[p], rank_first[p], dense_before[p], held[p] = before, first_rank, dense - 1, e["n"]
        before += e["n"]
        last_rank = first_rank if e["d"] == 1 else before - e["n_last"] + 1
        dense_last = dense + e["d"] - 1
    reach = 0
    for i in range(len(edges) - 1, -1, -1):
        e, after = edges[i], edges[i + 1] if i + 1 < len(edges) else None
        end = base[e[PART]] + e["n"]
        if after and after["joined"]:
            up_to_last[e[PART]] = reach if after["d"] == 1 else end + after["n_first"]
        else:
            up_to_last[e[PART]] = end
        reach = up_to_last[e[PART]]
    part = F.col(PART)
    key_only = Window.partitionBy(PART).orderBy(sf.key.order()[0])
    up_to = F.count(F.lit(1)).over(key_only.rangeBetween(Window.unboundedPreceding, Window.currentRow))
    own = F.rank().over(key_only)
    return (
        move(sf.parted, sf.parts).withColumn("__own", own)
        .withColumn("__up_to", up_to)
        .withColumn("dense_rank", (_before(dense_before, part) + F.dense_rank().over(key_only)).cast("long"))
        .withColumn("rank", F.when(F.col("__own") == 1, _before(rank_first, part)).otherwise(_before(base, part) + F.col("__own")).cast("long"))
        .withColumn("percent_rank", (F.col("rank") - 1) / F.lit(float(max(total - 1, 1))))
        .withColumn("cume_dist", F.when(F.col("__up_to") == _before(held, part), _before(up_to_last, part)).otherwise(_before(base, part) + F.col("__up_to")) / F.lit(float(max(total, 1))))
        .select(*[c for c in sf.df.columns if c != PART], "rank", "dense_rank", "percent_rank", "cume_dist")
    )


def ntile(sf: SortedFrame, tiles: int, name: str = "tile") -> DataFrame:
    """Rows with their tile, the first ones a row larger if the rows don't divide evenly."""
    placed = global_position(sf, "__place", "window")
    n = sf.sizes.n if sf.sizes.exact else sf.parted.count()
    small, larger = divmod(n, tiles)
    edge = larger * (small + 1)
    place = F.col("__place") - 1
    tile = F.when(place < edge, F.floor(place / F.lit(small + 1))).otherwise(larger + F.floor((place - edge) / F.lit(max(small, 1))))
    return placed.withColumn(name, (tile + 1).cast("int")).drop("__place")


def ranked_keys(keys: DataFrame) -> DataFrame:
    """Column ``x`` with its 0-based ``rank`` in the sorted order, by a partition sort."""
    placed = global_position(linear_partition_sort(keys.where("x is not null"), "x"), "rank")
    return placed.select("x", (F.col("rank") - 1).alias("rank"))


def cumulative(df: DataFrame, key: str) -> tuple[DataFrame, int]:
    """Distinct keys as ``x`` with their ``rows`` and the rows ``up_to`` them, and the rows of all keys.

    Rows are counted by key before anything is sorted, so a key that holds many
    of them weighs no more than another. Null keys are left out.
    """
    counts = df.where(F.col(key).isNotNull()).groupBy(F.col(key).alias("x")).agg(F.count("*").alias("rows"))
    sf = linear_partition_sort(materialize(counts, "key-counts"), KeySpec("x"))
    held = {r[PART]: r["n"] for r in sf.df.groupBy(PART).agg(F.sum("rows").alias("n")).collect()}  # a row a part
    before, total = [], 0
    for part in range(sf.parts):
        before.append(total)
        total += held.get(part, 0)
    up_to = F.sum("rows").over(Window.partitionBy(PART).orderBy("x").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    return sf.df.select("x", "rows", (_before(before, F.col(PART)) + up_to).cast("long").alias("up_to")), total


def exact_ecdf(df: DataFrame, key: str) -> DataFrame:
    """``df`` with ``ecdf``, the share of keys at or below, and ``position`` = floor(N * ecdf); null keys are left out."""
    steps, n = cumulative(df, key)
    steps = steps.select(F.col("x").alias("__x"), (F.col("up_to") / F.lit(float(max(n, 1)))).alias("ecdf"), F.col("up_to").alias("position"))
    return df.join(steps, df[key] == steps["__x"]).drop("__x")
