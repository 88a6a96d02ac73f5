"""Cost and accuracy measures of models and sorters."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from modelsort.functions import sampling
from modelsort.functions.keys import KeySpec, numeric, valid
from modelsort.functions.models import EcdfBucket, LinearBucket, Model, Rmi
from modelsort.functions.models.linear import FITS
from modelsort.operators.rank import cumulative, global_position
from modelsort.operators.sorters import SortedFrame, linear_partition_sort
from modelsort.plans.durable import materialize
from modelsort.plans.partitioner import PART


def bucket_counts(df: DataFrame, x: Column, model: Model) -> DataFrame:
    """Columns ``bucket, rows`` for all buckets of the model, empty ones included."""
    every = df.sparkSession.range(model.buckets).select(F.col("id").cast("int").alias("bucket"))
    found = df.where(x.isNotNull() & ~F.isnan(x)).groupBy(model.column(x).cast("int").alias("bucket")).agg(F.count("*").alias("rows"))
    return every.join(found, "bucket", "left").select("bucket", F.coalesce("rows", F.lit(0)).cast("long").alias("rows"))


def balance(counts: DataFrame) -> DataFrame:
    """``imbalance`` (squared deviations from equal sizes), ``max_share``, ``empty_share`` of bucket counts."""
    n, k = F.sum("rows"), F.count("*")
    # The sum of squared deviations from N/k, written without a second pass.
    spread = F.sum(F.col("rows").cast("double") * F.col("rows")) - n.cast("double") * n / k
    return counts.agg(spread.alias("imbalance"), (F.max("rows") / n).alias("max_share"), (F.count(F.when(F.col("rows") == 0, 1)) / k).alias("empty_share"))


def _in_order(df: DataFrame, x: Column, ties: list[Column], **more: Column) -> SortedFrame:
    """Rows with a key, sorted by ``x`` and the ties ``t0, t1, ...`` in one shuffle."""
    names = tuple(f"t{i}" for i in range(len(ties)))
    rows = df.where(x.isNotNull()).select(x.alias("x"), *(t.alias(c) for t, c in zip(ties, names, strict=True)), *(c.alias(name) for name, c in more.items()))
    return linear_partition_sort(rows, KeySpec("x", ties=names))


def falls(df: DataFrame, key: KeySpec, value: str) -> DataFrame:
    """Column ``falls``: rows whose ``value`` is under that of the row before in the order of parts and an ascending key."""
    here = Window.partitionBy(PART).orderBy(*key.order())
    rows = df.withColumn("__last", F.lag(value).over(here))
    ends = F.struct(*(F.col(c) for c in (key.column, *key.ties)))
    parts = rows.groupBy(PART).agg(F.count(F.when(F.col(value) < F.col("__last"), 1)).alias("inner"), F.min_by(value, ends).alias("first"), F.max_by(value, ends).alias("last"))
    border = F.lag("last").over(Window.orderBy(PART))  # a row a part
    return parts.withColumn("border", border).agg((F.coalesce(F.sum("inner"), F.lit(0)) + F.count(F.when(F.col("first") < F.col("border"), 1))).cast("long").alias("falls"))


def bucket_mse(df: DataFrame, x: Column, model: Model, ties: list[Column]) -> DataFrame:
    """Mean squared distance between a row's bucket and k times its share of the order."""
    sf = _in_order(df, x, ties)
    n = float(max(sf.sizes.n, 1))
    placed = global_position(sf)
    target = F.lit(float(model.buckets)) * (F.col("position") - 1) / F.lit(n)
    return placed.select(F.pow(model.column(F.col("x")) - target, 2).alias("e")).agg(F.avg("e").alias("mse"))


def ecdf_error(df: DataFrame, x: Column, predicted: Callable[[Column], Column]) -> DataFrame:
    """Largest and mean miss of an eCDF model over all rows, and the digits that the last mile leaves."""
    steps, n = cumulative(df.select(x.alias("x")), "x")
    miss = steps.select(F.abs(predicted(F.col("x")) - F.col("up_to") / F.lit(float(max(n, 1)))).alias("e"), "rows")
    mean = F.sum(F.col("e") * F.col("rows")) / F.sum("rows")
    return miss.agg(F.max("e").alias("max_error"), mean.alias("mean_error"), (-F.log10(F.greatest(mean, F.lit(1e-15)))).alias("last_mile"))


def violations(df: DataFrame, x: Column, predicted: Callable[[Column], Column]) -> DataFrame:
    """Neighbours in key order whose predictions fall."""
    keys = df.where(x.isNotNull()).select(x.alias("x")).distinct()
    sf = linear_partition_sort(keys, KeySpec("x"))
    return falls(sf.df.withColumn("f", predicted(F.col("x"))), sf.key, "f").select(F.col("falls").alias("violations"))


def collisions(df: DataFrame, x: Column, slot: Column) -> DataFrame:
    """Rows that share their slot with a different key, and rows that must since they repeat a key."""
    slots = df.where(x.isNotNull()).groupBy(slot.alias("slot")).agg(F.count("*").alias("rows"), F.count_distinct(x).alias("keys"))
    return slots.agg(F.coalesce(F.sum(F.when(F.col("keys") > 1, F.col("rows"))), F.lit(0)).alias("colliding_rows"), F.coalesce(F.sum(F.col("rows") - F.col("keys")), F.lit(0)).alias("forced_rows"))


def displacement(df: DataFrame, x: Column, predicted: Column, ties: list[Column]) -> DataFrame:
    """Rows out of place in the order of the prediction, how far they are, and adjacent inversions."""
    placed = materialize(global_position(_in_order(df, x, ties, f=predicted), "k"), "key-order")
    names = [c for c in placed.columns if c not in ("x", "f", "k")]
    given = _in_order(placed, F.col("f"), [F.col(c) for c in names], key=F.col("x"), k=F.col("k"))
    moved = global_position(given, "g").agg(F.count(F.when(F.col("k") != F.col("g"), 1)).alias("moved"), F.max(F.abs(F.col("k") - F.col("g"))).cast("long").alias("farthest"))
    return moved.crossJoin(falls(given.df, given.key, "key").select(F.col("falls").alias("inversions")))  # a row each


def sample_sweep(df: DataFrame, key: str, fractions: tuple[float, ...], k: int = 256, leaves: int = 128, seed: int = 42) -> list[dict]:
    """How a sample's share trades time for eCDF error and balance, both over all keys.

    Seconds are given apart for the sample, the fit and one prediction of all
    keys. The sample is written, and the two-level eCDF and the equal ranges
    fitted on it need a row a leaf on the driver, so any share will do.
    """
    import time

    keys = df.select(numeric(df, key).alias("x")).where(valid(F.col("x")))
    steps, n = cumulative(keys, "x")
    steps = materialize(steps, "ecdf")
    rows = []
    for fraction in fractions:
        clock = [time.perf_counter()]
        sample = materialize(keys.sample(fraction, seed) if fraction < 1 else keys, "sample")
        size = sample.count()
        clock.append(time.perf_counter())
        model = Rmi.two_level_distributed(sample, "x", leaves)
        clock.append(time.perf_counter())
        share = model.column(F.col("x"))
        miss = F.abs(share - F.col("up_to") / F.lit(float(max(n, 1))))
        found = steps.agg((F.sum(miss * F.col("rows")) / F.sum("rows")).alias("e")).first()["e"]
        clock.append(time.perf_counter())
        largest = steps.groupBy(EcdfBucket(model, k).column(F.col("x")).alias("b")).agg(F.sum("rows").alias("rows")).agg(F.max("rows")).first()[0]
        times = dict(zip(("sample_s", "train_s", "predict_s"), np.diff(clock).tolist(), strict=True))
        rows.append({"fraction": fraction, "sampled": size, "ecdf_error": float(found) if found is not None and size else 1.0, "max_share": float((largest or 0) / max(n, 1))} | times)
    return rows


def oversampling_sweep(df: DataFrame, key: str, factors: tuple[float, ...] = (0.05, 0.1, 0.2, 0.4, 0.8), k: int = 256, seed: int = 42) -> list[dict]:
    """Balance of the least-conflict line on all keys by the factor of the logarithm in its sample's size."""
    keys = df.select(numeric(df, key).alias("x")).where(valid(F.col("x")))
    n = keys.count()
    rows = []
    for factor in factors:
        size = sampling.sample_size(max(n, 2), k, factor)
        line = LinearBucket.fit_min_conflict(sampling.draw(keys, F.col("x"), size, max(n, 1), seed), k)
        found = balance(bucket_counts(keys, F.col("x"), line)).first()
        rows.append({"factor": factor, "sampled": min(size, n), "conflict": line.conflict, "imbalance": found["imbalance"], "max_share": found["max_share"]})
    return rows


def shuffled_rows(df: DataFrame, sorter: Callable[[DataFrame], SortedFrame]) -> dict:
    """Rows that rounds of partitioning would move one by one, against the single move of the payload."""
    sf = sorter(df)
    n = df.count()
    return {"rounds": sf.trace.rounds, "moved_once": n, "moved_by_rounds": n + sum(sf.trace.looked_at), "parts": sf.parts}


def fit_ablation(df: DataFrame, key: str, ks: tuple[int, ...] = (16, 64, 256, 1024, 4096, 16_384, 65_536), seed: int = 42) -> list[dict]:
    """Balance of every line fit and number of buckets on all keys of a column, counted in one pass."""
    x = numeric(df, key)
    keys = df.select(x.alias("x")).where(valid(F.col("x")))
    n = keys.count()
    tried = []
    for k in ks:
        sample = sampling.draw(df, x, sampling.sample_size(max(n, 2), k), n, seed)
        tried += [(k, name, fit(sample, k)) for name, fit in FITS.items()]
    buckets = F.posexplode(F.array(*(m.column(F.col("x")).cast("int") for _, _, m in tried))).alias("i", "bucket")
    counts = keys.select(buckets).groupBy("i", "bucket").agg(F.count("*").alias("rows"))
    found = {r["i"]: r for r in counts.groupBy("i").agg(F.sum(F.col("rows").cast("double") * F.col("rows")).alias("square"), F.max("rows").alias("most"), F.count("*").alias("used")).collect()}  # a row a fit
    rows = []
    for i, (k, name, model) in enumerate(tried):
        r = found.get(i) or {"square": 0.0, "most": 0, "used": 0}
        rows.append({"key": key, "k": k, "fit": name, "conflict": model.conflict, "imbalance": float(r["square"]) - n * n / k, "max_share": float(r["most"] / max(n, 1)), "empty_share": 1 - r["used"] / k})
    return rows


def op_model(n: int, word_bits: int = 64, digit_bits: int = 8) -> dict[str, float]:
    """Operation counts that the complexity statements give for ``n`` keys."""
    return {"comparison_sort": n * math.log2(max(n, 2)), "radix_sort": n * word_bits / digit_bits, "linear_rounds": math.log(max(n, 3)) / math.log(3), "ideal": float(n)}


def leaderboard(results: DataFrame) -> DataFrame:
    """Sorters ranked by rate within family and data set, with roll-ups to family and to all.

    ``results`` has ``family, dataset, sorter, keys_per_s``.
    """
    means = results.groupingSets([["family", "dataset", "sorter"], ["family", "sorter"], ["sorter"]], "family", "dataset", "sorter").agg(F.avg("keys_per_s").alias("keys_per_s"), F.grouping_id().alias("level"))
    best = Window.partitionBy("level", "family", "dataset").orderBy(F.desc("keys_per_s"), "sorter")
    return means.withColumn("rank", F.rank().over(best))


def pivoted(results: DataFrame, sorters: list[str]) -> DataFrame:
    """Mean rates with a column for each of the named sorters."""
    return results.groupBy("family", "dataset").pivot("sorter", sorters).agg(F.avg("keys_per_s"))


def unpivoted(wide: DataFrame, sorters: list[str]) -> DataFrame:
    """Rows of ``pivoted`` again; sorters without a rate are left out."""
    return wide.unpivot(["family", "dataset"], sorters, "sorter", "keys_per_s").where("keys_per_s is not null")


def crossover(rates: DataFrame, a: str, b: str) -> DataFrame:
    """By ``n``, the rate of sorter ``a`` over that of ``b``, and whether ``a`` is ahead."""
    wide = rates.groupBy("n").pivot("sorter", [a, b]).agg(F.max("keys_per_s"))
    return wide.select("n", (F.col(a) / F.col(b)).alias("speed_up"), (F.col(a) > F.col(b)).alias("ahead"))
