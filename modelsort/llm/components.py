"""Connected components by star contraction, on DataFrames only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from modelsort.plans.durable import materialize


def _with_least(pairs: DataFrame) -> DataFrame:
    """Add ``m``, the least of ``u`` and all its ``v``; minima are combined before the shuffle."""
    least = pairs.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
    return pairs.join(least, "u")


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _with_least(both).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    near = _with_least(down)
    hooked = near.select(F.col("v").alias("u"), F.col("m").alias("v"))
    return hooked.unionByName(near.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def connected_components(edges: DataFrame, tag: str = "components") -> DataFrame:
    """Columns ``u, v`` (longs, any direction) to ``node, component`` (least node reachable).

    Only nodes with an edge to another node appear. Loops, repeated edges and
    rows with a null end are ignored; no edges give no rows. Rounds are
    logarithmic in practice; each is written to the shared folder, so a lost
    executor repeats one round at most. The driver holds two sums a round.
    """
    current = materialize(edges.select("u", "v").where("u <> v").distinct(), tag)
    before = None
    while True:
        state = current.agg(F.count("*"), F.sum(F.pmod(F.xxhash64("u", "v"), F.lit(1 << 40)))).first()
        if state == before or not state[0]:
            return current.select(F.col("u").alias("node"), F.col("v").alias("component"))
        before = state
        current = materialize(_small_star(_large_star(current)), tag)
