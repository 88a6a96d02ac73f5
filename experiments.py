"""The reference's experiments on generated keys: rates, rankings, scaling, balance.

python experiments.py [rates|scaling|balance|phases] [--n N] [--sequential]

``rates`` runs every sorter on every data set of the real, synthetic and
duplicate families and prints ranks; ``scaling`` goes through sizes of normal
keys and prints speed-ups over the library; ``balance`` reports bucket measures;
``phases`` prints the seconds of sample, training and prediction by sample share.
``--sequential`` uses one core and adds the sequential forms.
"""

from __future__ import annotations

import argparse
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from modelsort.functions.keys import KeySpec
from modelsort.operators import metrics, sorters
from modelsort.sources import datasets

KEY = KeySpec("key", ties=("id",))
SORTERS = {
    "linear": lambda df: sorters.linear_partition_sort(df, KEY).df,
    "tree": lambda df: sorters.tree_sample_sort(df, KEY).df,
    "radix": lambda df: sorters.radix_partition_sort(df, KEY).df,
    "ecdf": lambda df: sorters.ecdf_two_pass_sort(df, KEY).df,
    "library": lambda df: sorters.builtin_sort(df, KEY),
}
BARE = {f"{m}_sequential": lambda df, m=m: sorters.sequential_sort(df.select(F.col("key").cast("double").alias("key")), "key", m) for m in sorters.SEQUENTIAL}


def measure(spark: SparkSession, family: str, name: str, n: int, which: dict) -> list[tuple]:
    """Rate of each sorter on keys written once beforehand; the better of two runs."""
    from modelsort.plans.durable import materialize

    df = materialize(datasets.keys(spark, name, n), "experiment")
    out = []
    for sorter, run in which.items():
        best = float("inf")
        for _ in range(2):
            start = time.perf_counter()
            run(df).write.format("noop").mode("overwrite").save()
            best = min(best, time.perf_counter() - start)
        out.append((family, name, sorter, n, best, n / best))
    return out


def rates(spark: SparkSession, n: int, which: dict) -> DataFrame:
    rows = [r for family, names in datasets.FAMILIES.items() for name in names for r in measure(spark, family, name, n, which)]
    return spark.createDataFrame(rows, "family string, dataset string, sorter string, n long, secs double, keys_per_s double")


def scaling(spark: SparkSession, sizes: list[int], which: dict) -> DataFrame:
    rows = [r for n in sizes for r in measure(spark, "scaling", "normal", n, which)]
    return spark.createDataFrame(rows, "family string, dataset string, sorter string, n long, secs double, keys_per_s double")


def balance(spark: SparkSession, n: int) -> DataFrame:
    rows = []
    for family, names in datasets.FAMILIES.items():
        for name in names:
            rows += [(family, name, r["k"], r["fit"], r["max_share"], r["empty_share"]) for r in metrics.fit_ablation(datasets.keys(spark, name, n), "key", (256,))]
    return spark.createDataFrame(rows, "family string, dataset string, k long, fit string, max_share double, empty_share double")


def main() -> None:
    args = argparse.ArgumentParser()
    args.add_argument("what", choices=["rates", "scaling", "balance", "phases"], nargs="?", default="rates")
    args.add_argument("--n", type=int, default=1_000_000)
    args.add_argument("--sequential", action="store_true")
    o = args.parse_args()
    conf = {"spark.master": "local[1]" if o.sequential else "local[8]", "spark.driver.memory": "8g", "spark.sql.shuffle.partitions": "1" if o.sequential else "8", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false"}
    spark = SparkSession.builder.config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    which = SORTERS | BARE if o.sequential else SORTERS
    if o.what == "rates":
        found = rates(spark, o.n, which)
        metrics.leaderboard(found).orderBy("level", "family", "dataset", "rank").show(500, False)
    elif o.what == "scaling":
        found = scaling(spark, [n for n in (10_000, 100_000, 1_000_000, 10_000_000) if n <= o.n], which).cache()
        found.groupBy("n").pivot("sorter").agg(F.round(F.first("keys_per_s"))).orderBy("n").show(50, False)
        for name in which:
            if name != "library":
                print(name)
                metrics.crossover(found, name, "library").orderBy("n").show(50, False)
    elif o.what == "phases":
        rows = metrics.sample_sweep(datasets.keys(spark, "normal", o.n), "key", (0.001, 0.01, 0.1, 1.0))
        spark.createDataFrame(rows).show(50, False)
    else:
        balance(spark, o.n).show(500, False)


if __name__ == "__main__":
    main()
