"""Experiment keys: generators, carriers among the given tables, and a generator data source."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

from modelsort.functions.keys import numeric
from modelsort.sources.io import read

# Components of the normal mixture (weight, mean, deviation); the reference leaves them open.
MIXTURE = [(0.15, -8.0, 0.5), (0.25, -3.0, 1.0), (0.2, 0.0, 0.25), (0.25, 4.0, 1.5), (0.15, 9.0, 0.75)]


def _uniform(seed: int, salt: int = 0) -> Column:
    """A uniform number in (0, 1) from the id alone, the same however rows are dealt."""
    return (F.pmod(F.xxhash64("id", F.lit(seed), F.lit(salt)), F.lit(1 << 52)).cast("double") + 0.5) / F.lit(float(1 << 52))


def _normal(seed: int, salt: int = 0) -> Column:
    return F.sqrt(-2 * F.log(_uniform(seed, 2 * salt + 1))) * F.cos(F.lit(2 * np.pi) * _uniform(seed, 2 * salt + 2))


def _mixture(seed: int) -> Column:
    u, out, share = _uniform(seed, 91), F.lit(0.0), 0.0
    z = _normal(seed, 46)
    for weight, mean, deviation in reversed(MIXTURE):
        share += weight
        out = F.when(u > 1 - share, F.lit(mean) + F.lit(deviation) * z) if share == weight else F.when(u > 1 - share + weight, out).otherwise(F.lit(mean) + F.lit(deviation) * z)
    return out


def _zipf(n: int, s: float, seed: int) -> Column:
    """Rank by the inverse of the continuous distribution with density x**-s on [1, n + 1)."""
    top = float(n + 1) ** (1 - s)
    return F.floor(F.pow(_uniform(seed) * (top - 1) + 1, F.lit(1 / (1 - s)))).cast("long")


def generator(name: str, n: int, seed: int) -> Column:
    """The key of a data set as a column of ``id``."""
    root = max(1, int(np.floor(np.sqrt(n))))
    makers: dict[str, Callable[[], Column]] = {
        "uniform": lambda: _uniform(seed) * float(n),
        "normal": lambda: _normal(seed),
        "lognormal": lambda: F.exp(0.5 * _normal(seed)),
        "mixture": lambda: _mixture(seed),
        "exponential": lambda: -F.log(_uniform(seed)) / 2,
        "chi_squared": lambda: sum((F.pow(_normal(seed, i), 2) for i in range(4)), F.lit(0.0)),
        "root_dups": lambda: F.pmod(F.col("id"), F.lit(root)),
        "two_dups": lambda: F.pmod(F.pmod(F.col("id"), F.lit(n)) * F.pmod(F.col("id"), F.lit(n)) + F.lit(n // 2), F.lit(n)),
        "zipf": lambda: _zipf(n, 0.75, seed),
        "location_ids": lambda: F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 62)),
        "edit_times": lambda: F.lit(1_000_000_000_000) + F.col("id") * 1_000 + F.floor(-F.log(_uniform(seed)) * 5_000).cast("long"),
        "network_ids": lambda: F.when(_uniform(seed, 5) < 0.97, F.floor(_uniform(seed) * float(n))).otherwise(F.floor(_uniform(seed, 6) * 1e12)).cast("long"),
        "popularity": lambda: F.round(F.exp(6 + 1.5 * _normal(seed))).cast("long"),
        "pickup_times": lambda: F.floor(_uniform(seed) * 365).cast("long") * 86_400 + F.floor((_uniform(seed, 7) + _uniform(seed, 8)) * 43_200).cast("long"),
        "cauchy": lambda: F.tan(F.lit(np.pi) * (_uniform(seed) - 0.5)),
        "lognormal_wide": lambda: F.exp(4 * _normal(seed)),
    }
    return makers[name]()


REAL = ["location_ids", "edit_times", "network_ids", "popularity", "pickup_times"]
SYNTHETIC = ["uniform", "normal", "lognormal", "mixture", "exponential", "chi_squared"]
DUPLICATES = ["root_dups", "two_dups", "zipf"]
FAMILIES = {"real": REAL, "synthetic": SYNTHETIC, "duplicates": [*DUPLICATES, "exponential", "chi_squared"]}


def keys(spark: SparkSession, name: str, n: int, seed: int = 42) -> DataFrame:
    """Columns ``id, key`` of a generated data set."""
    return keys_of(spark.range(n), name, n, seed)


def keys_of(ids: DataFrame, name: str, n: int, seed: int = 42) -> DataFrame:
    """Generated keys of the ``n`` rows of ``ids`` (column ``id``)."""
    return ids.select("id", generator(name, n, seed).alias("key"))


def carrier(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """Columns ``id, key``: a given column of like shape for each data set of the experiments."""
    t = lambda table, *c: read(spark, folder, table, list(c))
    events, lines = t("events", "event_id", "ts", "user_id", "value"), t("lineitem", "l_orderkey", "l_extendedprice", "l_shipdate", "l_quantity", "l_discount")
    coordinates = lambda: t("embeddings", "vec_id", "embedding", "label").select("vec_id", "label", F.posexplode("embedding").alias("i", "c")).select((F.col("vec_id") * 64 + F.col("i")).alias("id"), F.col("c").cast("double").alias("c"), "label")
    line_id = F.xxhash64(*lines.columns)
    n = lambda df: df.count()
    makers: dict[str, Callable[[], DataFrame]] = {
        "location_ids": lambda: lines.select(line_id.alias("id"), F.col("l_orderkey").alias("key")),
        "edit_times": lambda: events.select(F.col("event_id").alias("id"), numeric(events, "ts").alias("key")),
        "network_ids": lambda: events.select(F.col("event_id").alias("id"), F.col("user_id").alias("key")),
        "popularity": lambda: t("documents", "doc_id", "n_chars").select(F.col("doc_id").alias("id"), F.col("n_chars").alias("key")),
        "pickup_times": lambda: lines.select(line_id.alias("id"), numeric(lines, "l_shipdate").alias("key")),
        "uniform": lambda: lines.select(line_id.alias("id"), F.col("l_extendedprice").alias("key")),
        "normal": lambda: coordinates().select("id", (8 * F.col("c")).alias("key")),
        "lognormal": lambda: coordinates().select("id", F.exp(4 * F.col("c")).alias("key")),
        "mixture": lambda: coordinates().select("id", (8 * F.col("c") + 6 * F.pmod("label", F.lit(5))).alias("key")),
        "exponential": lambda: events.select(F.col("event_id").alias("id"), (F.col("value") / 100).alias("key")),
        "chi_squared": lambda: t("embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("id"), F.aggregate(F.slice("embedding", 1, 4), F.lit(0.0), lambda a, x: a + 64 * x.cast("double") * x.cast("double")).alias("key")),
        "root_dups": lambda: events.select(F.col("event_id").alias("id"), F.pmod(F.col("event_id"), F.lit(max(1, int(np.sqrt(n(events)))))).alias("key")),
        "two_dups": lambda: _two_dups(events.select(F.col("event_id").alias("id")), n(events)),
        "zipf": lambda: _word_ranks(t("documents", "doc_id", "text")),
        "quantity": lambda: lines.select(line_id.alias("id"), F.col("l_quantity").alias("key")),
        "discount": lambda: lines.select(line_id.alias("id"), F.col("l_discount").alias("key")),
    }
    return makers[name]()


def _two_dups(ids: DataFrame, n: int) -> DataFrame:
    return ids.select("id", F.pmod(F.pmod("id", F.lit(n)) * F.pmod("id", F.lit(n)) + F.lit(n // 2), F.lit(n)).alias("key"))


def _word_ranks(docs: DataFrame) -> DataFrame:
    """Each word of the texts coded by its frequency rank (ties share a rank); the words are counted once, for all scans of the ranking."""
    from modelsort.operators.rank import ranks
    from modelsort.operators.sorters import linear_partition_sort
    from modelsort.plans.durable import materialize

    words = docs.select("doc_id", F.posexplode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("i", "word")).where("word <> ''")
    counts = materialize(words.groupBy("word").agg((-F.count("*")).alias("rows")), "word-counts")
    from modelsort.functions.keys import KeySpec

    rank = ranks(linear_partition_sort(counts, KeySpec("rows", ties=("word",)))).select("word", F.col("rank").alias("key"))
    # The ranks have a row a word: a part of them is held, and the words themselves need no sort.
    return words.join(rank.hint("shuffle_hash"), "word").select(F.xxhash64("doc_id", "i").alias("id"), "key")


class _KeyReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.n, self.seed = int(options.get("n", "1000")), int(options.get("seed", "42"))
        self.dist, self.split = options.get("dist", "uniform"), int(options.get("partitions", "4"))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.split)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        low, high = self.n * partition.value // self.split, self.n * (partition.value + 1) // self.split
        yield key_batch(self.dist, low, high, self.n, self.seed)


def key_batch(dist: str, low: int, high: int, n: int, seed: int) -> pa.RecordBatch:
    """Ids ``low`` to ``high`` with keys of a distribution that numpy draws; each id block has its own stream."""
    ids = np.arange(low, high)
    rng = np.random.default_rng([seed, low])
    draws = {"uniform": lambda: rng.uniform(0, n, len(ids)), "normal": lambda: rng.normal(size=len(ids)), "lognormal": lambda: rng.lognormal(0, 0.5, len(ids)), "exponential": lambda: rng.exponential(0.5, len(ids)), "root_dups": lambda: (ids % max(1, int(np.sqrt(n)))).astype(float)}
    return pa.RecordBatch.from_arrays([pa.array(ids), pa.array(draws[dist]())], names=["id", "key"])


class _KeyStream(SimpleDataSourceStreamReader):
    def __init__(self, options: dict[str, str]):
        self.reader, self.step = _KeyReader(options), int(options.get("rows_per_batch", "1000"))

    def initialOffset(self) -> dict:
        return {"row": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        stop = min(self.reader.n, start["row"] + self.step)
        return self._rows(start["row"], stop), {"row": stop}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return self._rows(start["row"], end["row"])

    def _rows(self, low: int, high: int) -> Iterator[tuple]:
        batch = key_batch(self.reader.dist, low, high, self.reader.n, self.reader.seed)
        return iter(list(zip(batch.column("id").to_pylist(), batch.column("key").to_pylist(), strict=True)))


class KeySource(DataSource):
    """``spark.read.format("keygen")`` with options dist, n, seed, partitions; streams take rows_per_batch."""

    @classmethod
    def name(cls) -> str:
        return "keygen"

    def schema(self) -> str:
        return "id long, key double"

    def reader(self, schema) -> DataSourceReader:
        return _KeyReader(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _KeyStream(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(KeySource)
