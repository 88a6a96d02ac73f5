"""Queries of the reference's own operators, and DuckDB SQL for what SQL can express.

Sorted outputs carry positions, whose SQL needs no model; fitted models are held
against the same search written in SQL.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

import numpy as np
from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from modelsort.functions import sampling
from modelsort.functions import sql as sql_functions
from modelsort.functions.keys import KeySpec, numeric, order_bits
from modelsort.functions.models import Composite, EcdfBucket, LinearBucket, RadixBucket, Rmi, SplitterTree, WithHeavy, tune_rmi
from modelsort.functions.models.linear import lsq_by_group, lsq_distributed, min_conflict_distributed, min_max_distributed
from modelsort.operators import aggs, blocks, joins, lookup, metrics, rank, sorters, topk, verify
from modelsort.operators.sorters import SortConfig
from modelsort.plans.durable import materialize, new_folder
from modelsort.plans.partitioner import PART, utilisation
from modelsort.sources import datasets, io, sinks
from modelsort.streaming import buckets as streaming

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}

LINE_TIES = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")
#: A line for events.value, as fitted on the portable sample.
LINE = LinearBucket(1.4823460752845055, -1.5496352494893415, 256, 12)
LINE_SQL = "CAST(floor(least(255.0, greatest(0.0, 1.4823460752845055 * CAST(value AS DOUBLE) + -1.5496352494893415))) AS INTEGER)"
#: Fixed splitters for events.value.
SPLITTERS = [2.0, 5.0, 10.0, 20.0, 40.0, 80.0, 160.0]
#: Keys, line and buffers of the worked example.
EXAMPLE = [18, 39, 33, 28, 25, 34, 11, 27, 47, 2, 48, 50, 10, 6, 36, 13, 9, 12, 22, 29]
EXAMPLE_LINE = LinearBucket(0.15, -1.55, 4)
EXAMPLE_BLOCK = 2


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)


def register(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(query: Query) -> Query:
        _QUERIES[name] = query
        if sql:
            _SQL[name] = sql
        return query

    return add


def table(spark: SparkSession, sf: str, name: str, *columns: str) -> DataFrame:
    return io.read(spark, sf, name, list(columns))


# ---------------------------------------------------------------- sorters


def _sorted(name: str, source: str, key: KeySpec, sorter: Callable, mode: str = "counter", key_sql: str | None = None, **options) -> None:
    """Register a sort whose result is the ties and their position."""
    order = f"{key_sql or key.column} {'ASC' if key.ascending else 'DESC'} NULLS {'FIRST' if key.nulls_first else 'LAST'}"
    ties = ", ".join(key.ties)

    def query(spark: SparkSession, sf: str) -> DataFrame:
        df = table(spark, sf, source, *dict.fromkeys([key.column, *key.ties]))
        return rank.global_position(sorter(df, key, **options), mode=mode).select(*key.ties, "position")

    register(name, f"SELECT {ties}, row_number() OVER (ORDER BY {order}, {ties}) AS position FROM {source}")(query)


VALUE = KeySpec("value", ties=("event_id",))
_sorted("linear_partition_sort_events_value", "events", VALUE, sorters.linear_partition_sort)
_sorted("linear_partition_sort_window_position", "events", VALUE, sorters.linear_partition_sort, mode="window")
_sorted("linear_partition_sort_totalprice", "orders", KeySpec("o_totalprice", ties=("o_orderkey",)), sorters.linear_partition_sort)
_sorted("linear_partition_sort_acctbal", "customer", KeySpec("c_acctbal", ties=("c_custkey",)), sorters.linear_partition_sort)
_sorted("linear_partition_sort_n_chars", "documents", KeySpec("n_chars", ties=("doc_id",)), sorters.linear_partition_sort)
_sorted("linear_partition_sort_ts", "events", KeySpec("ts", ties=("event_id",)), sorters.linear_partition_sort)
_sorted("linear_partition_sort_shipdate", "lineitem", KeySpec("l_shipdate", ties=LINE_TIES), sorters.linear_partition_sort)
_sorted("linear_partition_sort_extendedprice", "lineitem", KeySpec("l_extendedprice", ties=LINE_TIES[:4]), sorters.linear_partition_sort)
_sorted("linear_partition_sort_discount_no_equality", "lineitem", KeySpec("l_discount", ties=LINE_TIES), sorters.linear_partition_sort, config=SortConfig(equality=False))
_sorted("linear_least_squares_sort", "events", VALUE, sorters.linear_partition_sort, fit="lsq")
_sorted("linear_min_max_sort", "events", VALUE, sorters.linear_partition_sort, fit="minmax")
_sorted("linear_balanced_sort", "events", VALUE, sorters.linear_partition_sort, fit="balanced")
_sorted("linear_sampled_histogram_sort", "events", VALUE, sorters.linear_partition_sort, config=SortConfig(histogram_share=0.2))
_sorted("tree_sample_sort_heap", "events", VALUE, sorters.tree_sample_sort, mode="window")
_sorted("tree_equality_sort_quantity", "lineitem", KeySpec("l_quantity", ties=LINE_TIES), sorters.tree_sample_sort)
_sorted("tree_no_equality_sort_discount", "lineitem", KeySpec("l_discount", ties=LINE_TIES), lambda df, key: sorters.tree_sample_sort(df, key, equality=False))
_sorted("tree_sample_sort_case", "events", VALUE, lambda df, key: sorters.tree_sample_sort(df, key, mode="case"))
_sorted("tree_sample_sort_arrow", "events", VALUE, lambda df, key: sorters.tree_sample_sort(df, key, mode="arrow"))
_sorted("quantile_sketch_sort", "events", VALUE, sorters.quantile_sort)
_sorted("two_way_sort", "events", VALUE, sorters.two_way_sort)
_sorted("radix_sort_user_id", "events", KeySpec("user_id", ties=("event_id",)), sorters.radix_partition_sort)
_sorted("radix_double_bits_sort", "events", VALUE, sorters.radix_partition_sort)
_sorted("ecdf_two_pass_sort_value", "events", VALUE, sorters.ecdf_two_pass_sort)
_sorted("ecdf_two_pass_sort_n_chars", "documents", KeySpec("n_chars", ties=("doc_id",)), sorters.ecdf_two_pass_sort)
_sorted("classic_copy_sort", "events", VALUE, sorters.classic_copy_sort)
_sorted("auto_sort_discount", "lineitem", KeySpec("l_discount", ties=LINE_TIES), sorters.auto_sort)
_sorted("auto_sort_value", "events", VALUE, sorters.auto_sort)
_sorted("sort_desc_totalprice", "orders", KeySpec("o_totalprice", False, False, ("o_orderkey",)), sorters.linear_partition_sort)
_sorted("sort_string_names", "customer", KeySpec("c_name", ties=("c_custkey",)), sorters.linear_partition_sort)
_sorted("sort_string_urls_desc", "pages", KeySpec("url", False, False, ("page_id",)), sorters.tree_sample_sort)
_sorted("sort_multi_key", "orders", KeySpec("o_orderdate", ties=("o_totalprice", "o_orderkey")), sorters.linear_partition_sort)


def _bare(name: str, source: str, key: str, sorter: Callable = sorters.linear_partition_sort, made: tuple[str, str] | None = None, **options) -> None:
    """Register a sort without ties, whose result is the key and the place where its rows lie; ``made`` computes it in Spark and DuckDB."""

    def query(spark: SparkSession, sf: str) -> DataFrame:
        df = table(spark, sf, source)
        df = df.select(F.expr(made[0]).alias(key)) if made else df.select(key)
        return rank.global_position(sorter(df, key, **options)).select(key, "position")

    register(name, f"SELECT {key}, row_number() OVER (ORDER BY {key}) AS position FROM (SELECT {made[1] if made else key} AS {key} FROM {source})")(query)


_bare("bare_sort_names", "customer", "c_name")
_bare("bare_sort_names_tree", "customer", "c_name", sorters.tree_sample_sort)
_bare("bare_sort_urls", "pages", "url")
_bare("bare_sort_urls_radix", "pages", "url", sorters.radix_partition_sort)
_bare("bare_sort_urls_ecdf", "pages", "url", sorters.ecdf_two_pass_sort)
_bare("bare_sort_texts", "documents", "text")
_bare("bare_sort_priorities", "orders", "o_orderpriority")
_bare("bare_sort_huge_integers", "orders", "k", made=("1152921504606846976L + o_orderkey % 8", "1152921504606846976 + o_orderkey % 8"))
_FINE = "CAST(concat('1234567890123456789.', lpad(CAST(o_orderkey AS {text}), 10, '0')) AS DECIMAL(38,10))"
_bare("bare_sort_fine_decimals", "orders", "k", made=(_FINE.format(text="STRING"), _FINE.format(text="VARCHAR")))
_HOT = "CASE WHEN event_id % 5 < 4 THEN 7.0 ELSE value END"
for _name in ("linear_partition_sort", "tree_sample_sort", "radix_partition_sort", "ecdf_two_pass_sort", "two_way_sort"):
    _bare(f"bare_hot_{_name}", "events", "k", getattr(sorters, _name), (_HOT, f"CAST({_HOT} AS DOUBLE)"))


def _derived(name: str, source: str, columns: str, expression: str, duck: str, key: KeySpec, sorter: Callable = sorters.linear_partition_sort) -> None:
    """Register a sort by a computed key ``k``."""
    order = f"k {'ASC' if key.ascending else 'DESC'} NULLS {'FIRST' if key.nulls_first else 'LAST'}, {', '.join(key.ties)}"

    def query(spark: SparkSession, sf: str) -> DataFrame:
        df = table(spark, sf, source, *columns.split()).withColumn("k", F.expr(expression))
        return rank.global_position(sorter(df, key)).select(*key.ties, "position")

    register(name, f"SELECT {', '.join(key.ties)}, row_number() OVER (ORDER BY {order}) AS position FROM (SELECT *, {duck} AS k FROM {source})")(query)


_derived("sort_nulls_first", "customer", "c_custkey c_acctbal", "CASE WHEN c_acctbal >= 0 THEN c_acctbal END", "CASE WHEN c_acctbal >= 0 THEN c_acctbal END", KeySpec("k", ties=("c_custkey",)))
_derived("sort_nulls_last", "customer", "c_custkey c_acctbal", "CASE WHEN c_acctbal >= 0 THEN c_acctbal END", "CASE WHEN c_acctbal >= 0 THEN c_acctbal END", KeySpec("k", nulls_first=False, ties=("c_custkey",)))
_derived("sort_desc_nulls_first", "customer", "c_custkey c_acctbal", "CASE WHEN c_acctbal >= 0 THEN c_acctbal END", "CASE WHEN c_acctbal >= 0 THEN c_acctbal END", KeySpec("k", False, True, ("c_custkey",)))
_derived("sort_json_key", "events", "event_id props", "CAST(get_json_object(props, '$.k') AS INT)", "CAST(json_extract_string(props, '$.k') AS INTEGER)", KeySpec("k", ties=("event_id",)))
_derived("sort_array_coordinate", "embeddings", "vec_id embedding", "CAST(embedding[0] AS DOUBLE)", "CAST(embedding[1] AS DOUBLE)", KeySpec("k", ties=("vec_id",)))
_derived("sort_decimal_key", "orders", "o_orderkey o_totalprice", "CAST(o_totalprice AS DECIMAL(18,2))", "CAST(o_totalprice AS DECIMAL(18,2))", KeySpec("k", ties=("o_orderkey",)))
_derived("sort_date_key", "orders", "o_orderkey o_orderdate", "CAST(o_orderdate AS DATE)", "CAST(o_orderdate AS DATE)", KeySpec("k", ties=("o_orderkey",)))

_derived("sort_hot_key_by_ties", "events", "event_id value", f"CAST({_HOT} AS DOUBLE)", f"CAST({_HOT} AS DOUBLE)", KeySpec("k", False, ties=("event_id",)))

POSITION_SQL = "SELECT event_id, row_number() OVER (ORDER BY value, event_id) AS position FROM events"


@register("builtin_sort_value", POSITION_SQL)
def _(spark: SparkSession, sf: str) -> DataFrame:
    ordered = sorters.builtin_sort(table(spark, sf, "events", "event_id", "value"), VALUE, sequential=True)
    return ordered.select("event_id", (F.monotonically_increasing_id() + 1).alias("position"))


@register("builtin_parallel_sort_descents", "SELECT CAST(0 AS BIGINT) AS descents")
def _(spark: SparkSession, sf: str) -> DataFrame:
    ordered = sorters.builtin_sort(table(spark, sf, "events", "event_id", "value"), VALUE).withColumn(PART, F.spark_partition_id()).withColumn("n", F.monotonically_increasing_id())
    return metrics.falls(ordered, KeySpec("n"), "value").select(F.col("falls").alias("descents"))


for _method in sorters.SEQUENTIAL:

    @register(f"sequential_{_method}_sort_value", "SELECT value, row_number() OVER (ORDER BY value) AS position FROM events")
    def _(spark: SparkSession, sf: str, method: str = _method) -> DataFrame:
        return sorters.sequential_sort(table(spark, sf, "events", "value"), "value", method)


@register("ideal_place_distinct", "SELECT event_id, event_id * 3 AS key, row_number() OVER (ORDER BY event_id) AS position FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return sorters.ideal_place(table(spark, sf, "events", "event_id").withColumn("key", F.col("event_id") * 3), "key")


@register("merge_sorted_runs", POSITION_SQL)
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "events", "event_id", "value")
    runs = [sorters.linear_partition_sort(df.where(F.col("event_id") % 2 == i), VALUE) for i in (0, 1)]
    return rank.global_position(sorters.merge_runs(runs)).select("event_id", "position")


#: Four lines as an eCDF of events.value; not monotone, so that there is something to correct.
ECDF_LINES = Rmi([1, 4], [np.array([0.004]), np.array([0.02, 0.002, 0.001, 0.0005])], [np.array([0.0]), np.array([0.05, 0.4, 0.55, 0.8])])
_LEAF = "CAST(floor(least(0.9999999999999999, greatest(0.0, CAST('0.004' AS DOUBLE) * value)) * 4) AS INTEGER) + 1"
_ECDF_SQL = f"least(0.9999999999999999, greatest(0.0, (CAST([0.02, 0.002, 0.001, 0.0005] AS DOUBLE[]))[{_LEAF}] * value + (CAST([0.05, 0.4, 0.55, 0.8] AS DOUBLE[]))[{_LEAF}]))"


@register("counting_sort_correction", f"SELECT event_id, slot, place, slot <> place AS moved FROM (SELECT event_id, row_number() OVER (ORDER BY least(n - 1, CAST(floor(f * n) AS BIGINT)), event_id) - 1 AS slot, row_number() OVER (ORDER BY value, event_id) - 1 AS place FROM (SELECT event_id, value, {_ECDF_SQL} AS f, count(*) OVER () AS n FROM events))")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "events", "event_id", "value").orderBy("event_id").coalesce(1)
    return sorters.counting_sort(df, VALUE, ECDF_LINES).select("event_id", "slot", "place", (F.col("slot") != F.col("place")).alias("moved"))


@register("page_of_order", "SELECT event_id, position FROM (SELECT event_id, row_number() OVER (ORDER BY value, event_id) AS position FROM events) WHERE position > 500 AND position <= 700")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return sorters.linear_partition_sort(table(spark, sf, "events", "event_id", "value"), VALUE).page(500, 200).select("event_id", "position")


for _method in ("linear", "tree", "radix", "ecdf", "auto"):

    @register(f"transform_sorted_by_{_method}", "SELECT c_name, row_number() OVER (ORDER BY c_name) AS position FROM customer")
    def _(spark: SparkSession, sf: str, method: str = _method) -> DataFrame:
        return rank.lying_position(table(spark, sf, "customer", "c_name").transform(sorters.sorted_by("c_name", method)))


@register("sort_proof", "SELECT CAST(0 AS BIGINT) AS within_parts, CAST(0 AS BIGINT) AS between_parts")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return verify.descents(sorters.linear_partition_sort(table(spark, sf, "events", "event_id", "value"), VALUE))


# ---------------------------------------------------------------- ranks


@register("rank_family_quantity", "SELECT DISTINCT l_quantity, rank() OVER w AS rank, dense_rank() OVER w AS dense_rank, round(percent_rank() OVER w, 9) AS percent_rank, round(cume_dist() OVER w, 9) AS cume_dist FROM lineitem WINDOW w AS (ORDER BY l_quantity)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    sf_ = sorters.linear_partition_sort(table(spark, sf, "lineitem", *LINE_TIES, "l_quantity"), KeySpec("l_quantity", ties=LINE_TIES))
    return rank.ranks(sf_).select("l_quantity", "rank", "dense_rank", F.round("percent_rank", 9).alias("percent_rank"), F.round("cume_dist", 9).alias("cume_dist")).distinct()


@register("ntile_value", "SELECT event_id, CAST(ntile(7) OVER (ORDER BY value, event_id) AS INTEGER) AS tile FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return rank.ntile(sorters.linear_partition_sort(table(spark, sf, "events", "event_id", "value"), VALUE), 7).select("event_id", "tile")


@register("ecdf_exact", "SELECT DISTINCT p_size, cume_dist() OVER (ORDER BY p_size) AS ecdf, CAST(round(cume_dist() OVER (ORDER BY p_size) * count(*) OVER ()) AS BIGINT) AS position FROM part")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return rank.exact_ecdf(table(spark, sf, "part", "p_size"), "p_size").distinct()


# ---------------------------------------------------------------- worked example

#: The example's line and buffers on the events of each user, in the order of their ids: step of a full block by the arrival of its last key.
_BUCKET_SQL = "CAST(floor(least(3.0, greatest(0.0, 0.15 * value + -1.55))) AS INTEGER)"
_STATES_SQL = f"""
WITH k AS (SELECT user_id, value AS key, {_BUCKET_SQL} AS bucket, row_number() OVER (PARTITION BY user_id ORDER BY event_id) - 1 AS i FROM events),
r AS (SELECT *, row_number() OVER (PARTITION BY user_id, bucket ORDER BY i) - 1 AS j, count(*) OVER (PARTITION BY user_id, bucket) AS n FROM k),
f AS (SELECT *, (j // 2 + 1) * 2 <= n AS whole, max(i) OVER (PARTITION BY user_id, bucket, j // 2) AS filled FROM r),
s AS (SELECT *, CAST(CASE WHEN whole THEN dense_rank() OVER (PARTITION BY user_id, whole ORDER BY filled) - 1 ELSE -1 END AS INTEGER) AS step FROM f)
"""


def _example(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events", "event_id", "user_id", "value")


def _example_states(spark: SparkSession, sf: str, take: Callable[[blocks.Blocks], list[tuple]], columns: str, block: int = EXAMPLE_BLOCK) -> DataFrame:
    return blocks.classify_groups(_example(spark, sf), "user_id", "event_id", "value", EXAMPLE_LINE, block, take, columns)


@register("worked_example_buckets", f"SELECT event_id AS idx, value AS key, {_BUCKET_SQL} AS bucket FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return _example(spark, sf).select(F.col("event_id").alias("idx"), F.col("value").alias("key"), EXAMPLE_LINE.column(F.col("value")).alias("bucket"))


@register("worked_example_sizes", f"SELECT bucket, count(key) AS rows FROM (SELECT CAST(unnest([0, 1, 2, 3]) AS INTEGER) AS bucket) LEFT JOIN (SELECT {_BUCKET_SQL} AS bucket, value AS key FROM events) USING (bucket) GROUP BY bucket")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.bucket_counts(_example(spark, sf), F.col("value"), EXAMPLE_LINE)


@register("worked_example_blocks", f"{_STATES_SQL} SELECT user_id, CAST(row_number() OVER (PARTITION BY user_id ORDER BY NOT whole, CASE WHEN whole THEN step ELSE bucket END, j) - 1 AS INTEGER) AS idx, key FROM s")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return _example_states(spark, sf, lambda b: list(enumerate(b.array())), "idx int, key double")


@register("worked_example_contiguous", f"{_STATES_SQL} SELECT user_id, CAST(row_number() OVER (PARTITION BY user_id ORDER BY bucket, j) - 1 AS INTEGER) AS idx, key FROM s")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return _example_states(spark, sf, lambda b: list(enumerate(x for bucket in b.contiguous() for x in bucket)), "idx int, key double")


@register("worked_example_sorted", "SELECT value AS key, row_number() OVER (ORDER BY value) AS position FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return rank.global_position(sorters.sort_with(_example(spark, sf).select(F.col("value").alias("key")), "key", EXAMPLE_LINE))


@register("block_trace_function", f"{_STATES_SQL} SELECT user_id, step, bucket, string_agg(CAST(key AS VARCHAR), ',' ORDER BY j) AS keys FROM s GROUP BY user_id, step, bucket")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """The table function on the values of each user in the order of their events."""
    sql_functions.register(spark)
    _example(spark, sf).createOrReplaceTempView("modelsort_events")
    arrays = "SELECT user_id, transform(sort_array(collect_list(struct(event_id, value))), x -> x.value) AS xs FROM modelsort_events GROUP BY user_id"
    return spark.sql(f"SELECT user_id, step, bucket, array_join(transform(keys, x -> CAST(x AS STRING)), ',') AS keys FROM ({arrays}), LATERAL block_trace(xs, 0.15D, -1.55D, 4, 2)")


# ---------------------------------------------------------------- fits

def _conflict_sql(t: str, x: str, by: str = "") -> str:
    """Least feasible degree by trying each: ranks D apart, joined; per group if ``by`` names one."""
    g, on, of = (f"{by}, ", f"USING ({by})", f"PARTITION BY {by}") if by else ("", "ON TRUE", "")
    same = f"AND {{a}}.{by} = {{b}}.{by}" if by else ""
    eq = lambda a, b: same.format(a=a, b=b)
    return f"""
WITH r AS (SELECT {g}x, row_number() OVER ({of} ORDER BY x) - 1 AS i, count(*) OVER ({of}) AS s FROM (SELECT {g}CAST({x} AS DOUBLE) AS x FROM {t})),
sizes AS (SELECT {g}max(s) AS s FROM r {f"GROUP BY {by}" if by else ""}),
d AS (SELECT {g}CAST(unnest(generate_series(1, CAST(s // 3 AS BIGINT))) AS BIGINT) AS d, s FROM sizes),
w AS (SELECT d.*, (hi.x - lo.x) / 254 AS u, lo.x AS first FROM d JOIN r lo ON lo.i = d.d {eq("lo", "d")} JOIN r hi ON hi.i = d.s - 1 - d.d {eq("hi", "d")}),
g AS (SELECT {"w." + by + ", " if by else ""}w.d, min(b.x - a.x) AS gap FROM w JOIN r a {f"ON a.{by} = w.{by}" if by else "ON TRUE"} JOIN r b ON b.i = a.i + w.d {eq("b", "w")} GROUP BY ALL),
ok AS (SELECT {"w." + by + ", " if by else ""}min(w.d) AS d FROM w JOIN g ON g.d = w.d {eq("g", "w")} WHERE gap >= u OR w.d = s // 3 GROUP BY ALL)
SELECT {"w." + by + ", " if by else ""}CAST(w.d AS INTEGER) AS conflict, 1 / u AS slope, 1 - (1 / u) * first AS intercept{", w.s AS keys" if by else ""} FROM w JOIN ok ON ok.d = w.d {eq("ok", "w")}"""


def _line_row(spark: SparkSession, line: LinearBucket) -> DataFrame:
    return spark.createDataFrame([(line.conflict, line.slope, line.intercept)], "conflict int, slope double, intercept double")


for _t, _x in (("events", "value"), ("documents", "n_chars"), ("customer", "c_acctbal")):

    @register(f"min_conflict_fit_{_x}", _conflict_sql(_t, _x))
    def _(spark: SparkSession, sf: str, t: str = _t, x: str = _x) -> DataFrame:
        return _line_row(spark, min_conflict_distributed(table(spark, sf, t, x), x, 256))


def drawn(spark: SparkSession, sf: str, t: str = "events", x: str = "value", k: int = 256) -> np.ndarray:
    """The training sample of a fit: random keys of the whole column, as many as the sorters take."""
    df = table(spark, sf, t, x)
    n = df.count()
    return sampling.draw(df, numeric(df, x), sampling.sample_size(max(n, 2), k), max(n, 1))


for _t, _x in (("events", "value"), ("documents", "n_chars"), ("customer", "c_acctbal")):

    @register(f"min_conflict_fit_{_x}_sampled")
    def _(spark: SparkSession, sf: str, t: str = _t, x: str = _x) -> DataFrame:
        return _line_row(spark, LinearBucket.fit_min_conflict(drawn(spark, sf, t, x), 256))


@register("lsq_fit_value", "SELECT round(regr_slope(y, x), 6) AS slope, round(regr_intercept(y, x), 6) AS intercept FROM (SELECT value AS x, 256 * (row_number() OVER (ORDER BY value) - 1) / count(*) OVER () AS y FROM events)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    line = lsq_distributed(table(spark, sf, "events", "value"), "value", 256)
    return spark.createDataFrame([(round(line.slope, 6), round(line.intercept, 6))], "slope double, intercept double")


@register("minmax_fit_value", "SELECT 256 / (max(value) - min(value)) AS slope, -(256 / (max(value) - min(value))) * min(value) AS intercept FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    line = min_max_distributed(table(spark, sf, "events", "value"), "value", 256)
    return spark.createDataFrame([(line.slope, line.intercept)], "slope double, intercept double")


@register("balanced_fit_value")
def _(spark: SparkSession, sf: str) -> DataFrame:
    line = LinearBucket.fit_balanced(drawn(spark, sf), 256)
    return spark.createDataFrame([(line.slope, line.intercept)], "slope double, intercept double")


@register("lsq_fit_by_group", "SELECT event_type, round(regr_slope(y, x), 6) AS slope, round(regr_intercept(y, x), 6) AS intercept, count(*) AS rows FROM (SELECT event_type, value AS x, 16 * (row_number() OVER (PARTITION BY event_type ORDER BY value) - 1) / count(*) OVER (PARTITION BY event_type) AS y FROM events) GROUP BY event_type")
def _(spark: SparkSession, sf: str) -> DataFrame:
    found = lsq_by_group(table(spark, sf, "events", "event_type", "value"), "event_type", "value", 16)
    return found.select("event_type", F.round("slope", 6).alias("slope"), F.round("intercept", 6).alias("intercept"), "rows")


@register("splitters_value", "SELECT DISTINCT x AS splitter FROM (SELECT value AS x, row_number() OVER (ORDER BY value) - 1 AS i, count(*) OVER () AS s FROM events) JOIN (SELECT unnest(generate_series(1, 15)) AS j) ON i = (j * s) // 16")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame([(float(x),) for x in SplitterTree.fit_distributed(table(spark, sf, "events", "value"), "value", 16).splitters], "splitter double")


@register("splitters_value_sampled")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame([(float(x),) for x in SplitterTree.fit(drawn(spark, sf, k=16), 16).splitters], "splitter double")


_RMI_SQL = """
WITH ends AS (SELECT count(*) AS s, min(value) AS x0, max(value) AS x1 FROM events),
root AS (SELECT s, x0, (s - 1) / s / (x1 - x0) AS a FROM ends),
owned AS (SELECT value, s, CAST(floor(least(0.9999999999999999, greatest(0, a * value + -a * x0)) * {m}) AS INTEGER) AS leaf FROM events, root),
leaves AS (SELECT leaf, count(*) AS n, min(value) AS lo, max(value) AS hi, max(s) AS s FROM owned GROUP BY leaf),
cut AS (SELECT *, (sum(n) OVER (ORDER BY leaf) - n) / s AS y0, sum(n) OVER (ORDER BY leaf) / s AS y2 FROM leaves),
lines AS (SELECT *, CASE WHEN hi > lo THEN ((y2 - 1 / s) - y0) / (hi - lo) ELSE 0 END AS slope FROM cut)
"""


@register("rmi_lines_value", _RMI_SQL.format(m=8) + "SELECT leaf, round(slope, 6) AS slope FROM lines")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "events", "value")
    model = Rmi.two_level_distributed(df, "value", 8)
    used = sorted(r[0] for r in df.select(model.leaf(F.col("value"))).distinct().collect())
    return spark.createDataFrame([(i, round(float(model.slopes[1][i]), 6)) for i in used], "leaf int, slope double")


@register("rmi_empty_leaves", _RMI_SQL.format(m=64) + "SELECT (64 - count(*)) / 64 AS empty_share FROM lines")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame([(Rmi.two_level_distributed(table(spark, sf, "events", "value"), "value", 64).empty_leaves(),)], "empty_share double")


@register("rmi_tuning")
def _(spark: SparkSession, sf: str) -> DataFrame:
    rows = tune_rmi(drawn(spark, sf), (4, 16, 64))
    return spark.createDataFrame([(r["leaves"], r["root"], r["leaf"], r["mean_error"], r["max_error"]) for r in rows], "leaves int, root string, leaf string, mean_error double, max_error double")


@register("fit_per_group", _conflict_sql("events", "value", "event_type"))
def _(spark: SparkSession, sf: str) -> DataFrame:
    return aggs.fit_per_group(table(spark, sf, "events", "event_type", "value"), "event_type", "value").select("event_type", "conflict", "slope", "intercept", "keys")


@register("double_bits_of_powers", "SELECT p_size, CAST(CASE WHEN p_size % 2 = 0 THEN (p_size + 1023) * 4503599627370496 ELSE -((p_size + 1023) * 4503599627370496) - 1 END AS BIGINT) AS bits FROM (SELECT DISTINCT p_size FROM part)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    powers = table(spark, sf, "part", "p_size").distinct()
    return powers.select("p_size", order_bits(F.pow(F.lit(2.0), F.col("p_size")) * F.when(F.col("p_size") % 2 == 0, 1.0).otherwise(-1.0)).alias("bits"))


@register("double_order_bits", "SELECT event_id, rank() OVER (ORDER BY value) AS place FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    coded = table(spark, sf, "events", "event_id", "value").withColumn("bits", order_bits(F.col("value")))
    return rank.ranks(sorters.linear_partition_sort(coded, KeySpec("bits", ties=("event_id",)))).select("event_id", F.col("rank").alias("place"))


# ---------------------------------------------------------------- buckets and measures


def _case_sql(splitters: list[float], x: str = "value") -> str:
    return " + ".join(f"CAST({x} > {s} AS INTEGER)" for s in splitters)


def _counts(name: str, model, bucket: str, t: str = "events", x: str = "value") -> None:
    sql = f"WITH b AS (SELECT {bucket} AS bucket, count(*) AS rows FROM {t} GROUP BY 1) SELECT i.bucket, coalesce(rows, 0) AS rows FROM (SELECT CAST(unnest(generate_series(0, {model.buckets - 1})) AS INTEGER) AS bucket) i LEFT JOIN b ON b.bucket = i.bucket"
    register(name, sql)(lambda spark, sf: metrics.bucket_counts(table(spark, sf, t, x), numeric(table(spark, sf, t, x), x), model))


_counts("bucket_histogram_linear", LINE, LINE_SQL)
_counts("bucket_histogram_mirrored", LINE.mirrored(), f"255 - {LINE_SQL}")
_counts("bucket_histogram_tree", SplitterTree(np.array(SPLITTERS), np.zeros(0), "case"), _case_sql(SPLITTERS))
_counts("bucket_histogram_tree_arrow", SplitterTree(np.array(SPLITTERS), np.zeros(0), "arrow"), _case_sql(SPLITTERS))
_counts("bucket_histogram_equality", SplitterTree(np.array([10.0, 20.0, 30.0]), np.array([20.0]), "case"), f"{_case_sql([10, 20, 30], 'l_quantity')} + CAST(l_quantity > 20 AS INTEGER) + CAST(l_quantity = 20 AS INTEGER)", "lineitem", "l_quantity")
_counts("bucket_histogram_heavy_line", WithHeavy(LinearBucket(0.1, -0.1, 5), np.array([7.0, 25.0])), "CAST(floor(least(4.0, greatest(0.0, CAST(0.1 AS DOUBLE) * l_quantity + CAST(-0.1 AS DOUBLE)))) AS INTEGER) + 2 * CAST(l_quantity > 7 AS INTEGER) + 2 * CAST(l_quantity > 25 AS INTEGER) + CAST(l_quantity IN (7, 25) AS INTEGER)", "lineitem", "l_quantity")
_counts("bucket_histogram_radix", RadixBucket.fit(0, 255, 4), "CAST(least(15, greatest(0, CAST(floor(value) AS BIGINT) >> 4)) AS INTEGER)")


@register("bucket_histogram_rmi", _RMI_SQL.format(m=16) + ", placed AS (SELECT CAST(least(63, floor(64 * least(0.9999999999999999, greatest(0, least(y2, greatest(y0, slope * value + (y0 - slope * lo))))))) AS INTEGER) AS bucket FROM owned JOIN lines USING (leaf)) SELECT bucket, count(*) AS rows FROM placed GROUP BY 1")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "events", "value")
    model = EcdfBucket(Rmi.two_level_distributed(df, "value", 16), 64)
    return metrics.bucket_counts(df, F.col("value"), model).where("rows > 0")


@register("balance_measures", f"WITH b AS (SELECT {LINE_SQL} AS bucket, count(*) AS rows FROM events GROUP BY 1) SELECT round(CAST(sum(rows * rows) AS DOUBLE) - CAST(sum(rows) AS DOUBLE) * sum(rows) / 256, 3) AS imbalance, max(rows) / sum(rows) AS max_share, (256 - count(*)) / 256 AS empty_share FROM b")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.balance(metrics.bucket_counts(table(spark, sf, "events", "value"), F.col("value"), LINE)).withColumn("imbalance", F.round("imbalance", 3))


@register("bucket_mean_squared_error", f"SELECT round(avg(e), 6) AS mse FROM (SELECT pow({LINE_SQL} - 256.0 * (row_number() OVER (ORDER BY value, event_id) - 1) / count(*) OVER (), 2) AS e FROM events)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.bucket_mse(table(spark, sf, "events", "event_id", "value"), F.col("value"), LINE, [F.col("event_id")]).select(F.round("mse", 6).alias("mse"))


_LINE_SHARE = "least(1.0, greatest(0.0, CAST(0.005 AS DOUBLE) * value + CAST(0.25 AS DOUBLE)))"


def _share(x):
    return F.least(F.lit(1.0), F.greatest(F.lit(0.0), F.lit(0.005) * x + F.lit(0.25)))


@register("ecdf_error", f"SELECT round(max(e), 9) AS max_error, round(avg(e), 9) AS mean_error, round(-log10(greatest(avg(e), 1e-15)), 6) AS last_mile FROM (SELECT abs({_LINE_SHARE} - cume_dist() OVER (ORDER BY value)) AS e FROM events)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    found = metrics.ecdf_error(table(spark, sf, "events", "value"), F.col("value"), _share)
    return found.select(F.round("max_error", 9).alias("max_error"), F.round("mean_error", 9).alias("mean_error"), F.round("last_mile", 6).alias("last_mile"))


@register("monotone_violations", "SELECT count(*) FILTER (WHERE f < b) AS violations FROM (SELECT f, lag(f) OVER (ORDER BY value) AS b FROM (SELECT value, pow(value - 40, 2) AS f FROM events))")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.violations(table(spark, sf, "events", "value"), F.col("value"), lambda x: F.pow(x - 40, F.lit(2)))


@register("monotone_repair", "SELECT CAST(0 AS BIGINT) AS violations")
def _(spark: SparkSession, sf: str) -> DataFrame:
    sample = drawn(spark, sf)
    return metrics.violations(table(spark, sf, "events", "value"), F.col("value"), Rmi.two_level(sample, 16, leaf="lsq").monotone(sample).column)


@register("collisions", f"SELECT CAST(coalesce(sum(rows) FILTER (WHERE keys > 1), 0) AS BIGINT) AS colliding_rows, CAST(coalesce(sum(rows - keys), 0) AS BIGINT) AS forced_rows FROM (SELECT count(*) AS rows, count(DISTINCT value) AS keys FROM events GROUP BY {LINE_SQL})")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.collisions(table(spark, sf, "events", "value"), F.col("value"), LINE.column(F.col("value")))


@register("displacement", f"SELECT count(*) FILTER (WHERE k <> g) AS moved, max(abs(k - g)) AS farthest, count(*) FILTER (WHERE value < last) AS inversions FROM (SELECT *, lag(value) OVER (ORDER BY g) AS last FROM (SELECT value, row_number() OVER (ORDER BY value, event_id) AS k, row_number() OVER (ORDER BY {LINE_SQL}, event_id) AS g FROM events))")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.displacement(table(spark, sf, "events", "event_id", "value"), F.col("value"), LINE.column(F.col("value")), [F.col("event_id")])


@register("worker_utilisation")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "events", "event_id", "value")
    found = [(name, utilisation(s.sizes.rows, 8), s.trace.rounds) for name, s in (("linear", sorters.linear_partition_sort(df, VALUE)), ("tree", sorters.tree_sample_sort(df, VALUE)), ("radix", sorters.radix_partition_sort(df, VALUE)))]
    return spark.createDataFrame(found, "sorter string, busy double, rounds int")


@register("refinement_trace")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = datasets.carrier(spark, sf, "zipf").select(F.col("key").cast("double").alias("key"), "id")
    trace = sorters.linear_partition_sort(df, KeySpec("key", ties=("id",)), config=SortConfig(parts=8, base_rows=1024)).trace
    return spark.createDataFrame(list(enumerate(trace.largest)), "round int, largest long")


@register("refinement_ends", "SELECT CAST(0 AS BIGINT) AS left_open")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Buckets of several values that are still too large after the last round, on keys with a heavy tail."""
    sf_ = sorters.linear_partition_sort(table(spark, sf, "events", "event_id").select(F.exp(F.col("event_id") % 400 / 20).alias("key")), "key", config=SortConfig(parts=8, base_rows=64, equality=False))
    return spark.createDataFrame([(sf_.trace.largest[-1],)], "left_open long")


@register("fit_ablation")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame(metrics.fit_ablation(table(spark, sf, "events", "value"), "value"), "key string, k long, fit string, conflict long, imbalance double, max_share double, empty_share double")


@register("oversampling_ablation")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return spark.createDataFrame(metrics.oversampling_sweep(table(spark, sf, "events", "value"), "value"), "factor double, sampled long, conflict long, imbalance double, max_share double")


@register("equality_ablation", "SELECT unnest([true, false]) AS equality, count(*) AS rows, count(DISTINCT l_discount) AS keys, CAST(0 AS BIGINT) AS descents FROM lineitem")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df, every = table(spark, sf, "lineitem", "l_discount"), None
    for equality in (True, False):
        found = verify.proof(sorters.linear_partition_sort(df, "l_discount", config=SortConfig(equality=equality))).withColumn("equality", F.lit(equality))
        every = found if every is None else every.unionByName(found)
    return every


@register("move_ablation")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df, rows = table(spark, sf, "lineitem", "l_extendedprice"), []
    for name in ("linear_partition_sort", "tree_sample_sort", "two_way_sort"):
        found = metrics.shuffled_rows(df, lambda d, n=name: getattr(sorters, n)(d, "l_extendedprice", config=SortConfig(parts=64, base_rows=256)))
        rows.append((name, found["rounds"], found["moved_once"], found["moved_by_rounds"]))
    return spark.createDataFrame(rows, "sorter string, rounds long, moved_once long, moved_by_rounds long")


@register("sample_size_sweep")
def _(spark: SparkSession, sf: str) -> DataFrame:
    rows = metrics.sample_sweep(table(spark, sf, "events", "value"), "value", (0.01, 0.05, 0.25, 1.0))
    return spark.createDataFrame(rows, "fraction double, sampled long, ecdf_error double, max_share double, sample_s double, train_s double, predict_s double").drop("sample_s", "train_s", "predict_s")


@register("phase_times", "SELECT unnest([0.01, 0.1, 1.0])::DOUBLE AS fraction, true AS sample, true AS train, true AS predict")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Whether seconds of sample, training and prediction were measured apart; the seconds themselves are printed by experiments.py."""
    rows = metrics.sample_sweep(table(spark, sf, "events", "value"), "value", (0.01, 0.1, 1.0))
    return spark.createDataFrame([(r["fraction"], r["sample_s"] > 0, r["train_s"] > 0, r["predict_s"] > 0) for r in rows], "fraction double, sample boolean, train boolean, predict boolean")


@register("operation_model", "SELECT user_id, n, n * log2(greatest(n, 2)) AS comparison_sort, n * 8.0 AS radix_sort FROM (SELECT user_id, count(*) AS n FROM events GROUP BY user_id)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Operation counts of sorting the events of each user."""
    counts = table(spark, sf, "events", "user_id").groupBy("user_id").agg(F.count("*").alias("n"))
    model = F.udf(lambda n: (metrics.op_model(n)["comparison_sort"], metrics.op_model(n)["radix_sort"]), "comparison_sort double, radix_sort double")
    return counts.withColumn("m", model("n")).select("user_id", "n", "m.*")


# ---------------------------------------------------------------- selection


def _frame(spark: SparkSession, sf: str) -> tuple[DataFrame, sorters.SortedFrame]:
    df = table(spark, sf, "events", "event_id", "user_id", "value")
    return df, sorters.linear_partition_sort(df, VALUE)


@register("topk_smallest", "SELECT event_id, value FROM events ORDER BY value, event_id LIMIT 100")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return topk.smallest(*_frame(spark, sf), 100).select("event_id", "value")


@register("quantile_exact", "SELECT q, quantile_disc(value, q) AS value FROM events, (SELECT CAST(unnest([0.1, 0.5, 0.99]) AS DOUBLE) AS q) GROUP BY q" .replace("quantile_disc(value, q)", "CASE q WHEN 0.1 THEN quantile_disc(value, 0.1) WHEN 0.5 THEN quantile_disc(value, 0.5) ELSE quantile_disc(value, 0.99) END"))
def _(spark: SparkSession, sf: str) -> DataFrame:
    df, frame = _frame(spark, sf)
    return spark.createDataFrame([(q, topk.quantile(df, frame, q)) for q in (0.1, 0.5, 0.99)], "q double, value double")


@register("quantile_exact_sampled_sizes", _SQL["quantile_exact"])
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "events", "event_id", "value")
    frame = sorters.linear_partition_sort(df, VALUE, config=SortConfig(histogram_share=0.02))
    return spark.createDataFrame([(q, topk.quantile(df, frame, q)) for q in (0.1, 0.5, 0.99)], "q double, value double")


@register("ntile_sampled_sizes", _SQL["ntile_value"])
def _(spark: SparkSession, sf: str) -> DataFrame:
    return rank.ntile(sorters.linear_partition_sort(table(spark, sf, "events", "event_id", "value"), VALUE, config=SortConfig(histogram_share=0.02)), 7).select("event_id", "tile")


@register("quantile_approximate", "SELECT true AS by_sketch, true AS by_model")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Whether the sketch's and the bucket sizes' median miss the middle of the order by 1 % and by a bucket at most."""
    df, frame = _frame(spark, sf)
    sketch, model = topk.approx_quantile(df, "value", 0.5).first()[0], topk.model_quantile(frame, 0.5)
    low, high = (F.avg(F.when(F.col("value") < v, 1.0).otherwise(0.0)) for v in (sketch, model))
    return df.agg((F.abs(low - 0.5) <= 0.01).alias("by_sketch"), (F.abs(high - 0.5) <= F.lit(float(frame.sizes.rows.max() / max(frame.sizes.n, 1)))).alias("by_model"))


@register("topk_per_group", "SELECT user_id, event_id, rank FROM (SELECT user_id, event_id, CAST(row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS INTEGER) AS rank FROM events) WHERE rank <= 3")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return topk.per_group(_frame(spark, sf)[0], "user_id", "value", 3, ties=("event_id",)).select("user_id", "event_id", "rank")


@register("range_filter_by_model", "SELECT event_id FROM events WHERE value BETWEEN 20 AND 25")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return topk.between(*_frame(spark, sf), 20.0, 25.0).select("event_id")


@register("in_filter_by_model", "SELECT event_id FROM events WHERE user_id IN (3, 17, 101)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "events", "event_id", "user_id")
    return topk.isin(df, sorters.linear_partition_sort(df, KeySpec("user_id", ties=("event_id",))), [3, 17, 101]).select("event_id")


@register("clipped_rows", "SELECT count(*) FILTER (WHERE 0.1 * value - 1 < 0) AS below, count(*) FILTER (WHERE 0.1 * value - 1 >= 16) AS above FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return topk.clipped(table(spark, sf, "events", "value"), "value", LinearBucket(0.1, -1.0, 16))


@register("payload_filter", "SELECT event_id, row_number() OVER (ORDER BY value, event_id) AS position FROM events WHERE event_type LIKE 'c%' OR user_id < 40")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "events", "event_id", "event_type", "user_id", "value")
    return rank.global_position(topk.where_payload(sorters.linear_partition_sort(df, VALUE), "event_type LIKE 'c%' OR user_id < 40")).select("event_id", "position")


@register("projection_in_order", "SELECT event_id, value, event_type, row_number() OVER (ORDER BY value, event_id) AS position FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "events", "event_id", "event_type", "user_id", "value")
    return rank.global_position(sorters.linear_partition_sort(df, VALUE).select("event_type"))


@register("rmi_lookup", "SELECT c_custkey, row_number() OVER (ORDER BY c_acctbal, c_custkey) - 1 AS pos FROM customer QUALIFY c_acctbal IS NOT NULL")
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "customer", "c_custkey", "c_acctbal")
    index = lookup.RmiIndex.build(df, "c_acctbal", ("c_custkey",), leaves=16, block=64)
    return index.lookup(df.select("c_acctbal")).select("c_custkey", "pos")


@register("binary_search_lookup", _SQL["rmi_lookup"])
def _(spark: SparkSession, sf: str) -> DataFrame:
    df = table(spark, sf, "customer", "c_custkey", "c_acctbal")
    index = lookup.RmiIndex.build(df, "c_acctbal", ("c_custkey",), leaves=16, block=64)
    return lookup.BinarySearch.build(index).lookup(df.select("c_acctbal")).select("c_custkey", "pos")


# ---------------------------------------------------------------- joins

_ORDERS, _LINES = "(SELECT o_orderkey AS k, o_totalprice FROM orders)", "(SELECT l_orderkey AS k, l_extendedprice FROM lineitem)"


def _sides(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    return table(spark, sf, "orders", "o_orderkey", "o_totalprice").withColumnRenamed("o_orderkey", "k"), table(spark, sf, "lineitem", "l_orderkey", "l_extendedprice").withColumnRenamed("l_orderkey", "k")


for _how in joins.HOW:
    if _how in ("left_semi", "left_anti"):
        _sql = f"SELECT k, o_totalprice FROM {_ORDERS} a WHERE {'NOT ' if _how == 'left_anti' else ''}EXISTS (SELECT 1 FROM {_LINES} b WHERE a.k = b.k)"
    else:
        _sql = f"SELECT k, o_totalprice, l_extendedprice FROM {_ORDERS} {_how.upper()} JOIN {_LINES} USING (k)"

    @register(f"model_merge_join_{_how}", _sql)
    def _(spark: SparkSession, sf: str, how: str = _how) -> DataFrame:
        return joins.merge(*_sides(spark, sf), "k", how)


for _how in joins.HOW:

    _sql = f"SELECT k, l_extendedprice FROM {_LINES} a WHERE {'NOT ' if _how == 'left_anti' else ''}EXISTS (SELECT 1 FROM {_ORDERS} b WHERE a.k = b.k)" if _how.startswith("left_") else f"SELECT k, l_extendedprice, o_totalprice FROM {_LINES} {_how.upper()} JOIN {_ORDERS} USING (k)"

    @register("salted_join" if _how == "inner" else f"salted_join_{_how}", _sql)
    def _(spark: SparkSession, sf: str, how: str = _how) -> DataFrame:
        orders, lines = _sides(spark, sf)
        return joins.salted(lines, orders, "k", how, heavy_share=0.0002)


_HOT_SIDES = "(SELECT CASE WHEN event_id % 3 = 0 THEN 5 ELSE user_id END AS k, event_id FROM events)", "(SELECT c_custkey AS k, c_acctbal FROM customer)"
for _how in joins.HOW:
    _semi = f"SELECT k, event_id FROM {_HOT_SIDES[0]} a WHERE {'NOT ' if _how == 'left_anti' else ''}EXISTS (SELECT 1 FROM {_HOT_SIDES[1]} b WHERE a.k = b.k)"

    @register(f"hot_key_merge_join_{_how}", _semi if _how.startswith("left_") else f"SELECT k, event_id, c_acctbal FROM {_HOT_SIDES[0]} {_how.upper()} JOIN {_HOT_SIDES[1]} USING (k)")
    def _(spark: SparkSession, sf: str, how: str = _how) -> DataFrame:
        events = table(spark, sf, "events", "event_id", "user_id").select(F.expr("CASE WHEN event_id % 3 = 0 THEN 5 ELSE user_id END").alias("k"), "event_id")
        return joins.merge(events, table(spark, sf, "customer", "c_custkey", "c_acctbal").withColumnRenamed("c_custkey", "k"), "k", how)


@register("hash_join", _SQL["model_merge_join_inner"])
def _(spark: SparkSession, sf: str) -> DataFrame:
    return joins.hashed(*_sides(spark, sf), "k")


_A, _B = "(SELECT c_custkey, c_acctbal FROM customer)", "(SELECT s_suppkey, s_acctbal FROM supplier)"


def _balances(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    return table(spark, sf, "customer", "c_custkey", "c_acctbal"), table(spark, sf, "supplier", "s_suppkey", "s_acctbal")


@register("band_join", f"SELECT c_custkey, s_suppkey FROM {_A} JOIN {_B} ON abs(c_acctbal - s_acctbal) <= 25")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return joins.band(*_balances(spark, sf), "c_acctbal", "s_acctbal", 25.0).select("c_custkey", "s_suppkey")


@register("interval_join", f"SELECT c_custkey, s_suppkey FROM {_A} JOIN {_B} ON c_acctbal BETWEEN s_acctbal AND s_acctbal + 40")
def _(spark: SparkSession, sf: str) -> DataFrame:
    a, b = _balances(spark, sf)
    return joins.intervals(a, b.withColumn("until", F.col("s_acctbal") + 40), "c_acctbal", "s_acctbal", "until").select("c_custkey", "s_suppkey")


@register("theta_join", f"SELECT c_custkey, s_suppkey FROM {_A} JOIN {_B} ON c_acctbal < s_acctbal")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return joins.theta(*_balances(spark, sf), "c_acctbal", "s_acctbal", "<").select("c_custkey", "s_suppkey")


_CLICKS, _VIEWS = "(SELECT event_id, user_id, event_id * 10 AS t FROM events)", "(SELECT event_id AS other, user_id, event_id * 10 + 4 AS u FROM events)"


def _moments(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    ev = table(spark, sf, "events", "event_id", "user_id")
    return ev.withColumn("t", F.col("event_id") * 10), ev.select(F.col("event_id").alias("other"), "user_id", (F.col("event_id") * 10 + 4).alias("u"))


@register("asof_join_backward", f"SELECT a.event_id, b.other, b.u FROM {_CLICKS} a ASOF LEFT JOIN (SELECT other, u FROM {_VIEWS}) b ON a.t >= b.u")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return joins.asof(*_moments(spark, sf), "t", "u", columns=("other",)).select("event_id", "other", "u")


@register("asof_join_by_user", f"SELECT a.event_id, b.other, b.u FROM {_CLICKS} a ASOF LEFT JOIN {_VIEWS} b ON a.user_id = b.user_id AND a.t >= b.u")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return joins.asof(*_moments(spark, sf), "t", "u", by="user_id", columns=("other",)).select("event_id", "other", "u")


@register("asof_join_forward_tolerance", f"SELECT event_id, CASE WHEN u - t <= 25 THEN other END AS other, CASE WHEN u - t <= 25 THEN u END AS u FROM (SELECT a.event_id, a.t, b.other, b.u FROM {_CLICKS} a ASOF LEFT JOIN (SELECT other, u FROM {_VIEWS}) b ON a.t <= b.u)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return joins.asof(*_moments(spark, sf), "t", "u", columns=("other",), direction="forward", tolerance=25.0).select("event_id", "other", "u")


# ---------------------------------------------------------------- aggregates


@register("sort_aggregate", "SELECT user_id, count(*) AS rows, min(value) AS least, max(value) AS most FROM events GROUP BY user_id")
def _(spark: SparkSession, sf: str) -> DataFrame:
    frame = sorters.linear_partition_sort(table(spark, sf, "events", "event_id", "user_id", "value"), KeySpec("user_id", ties=("event_id",)))
    return aggs.sorted_group(frame, F.count("*").alias("rows"), F.min("value").alias("least"), F.max("value").alias("most"))


@register("hash_aggregate", _SQL["sort_aggregate"])
def _(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events", "user_id", "value").groupBy("user_id").agg(F.count("*").alias("rows"), F.min("value").alias("least"), F.max("value").alias("most"))


@register("bucket_distinct", "SELECT count(DISTINCT value) AS distinct_keys FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return aggs.distinct_count(_frame(spark, sf)[1])


@register("approximate_distinct", "SELECT count(DISTINCT user_id) AS exact, true AS approx, true AS hll FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """The exact count and whether both sketches are within a tenth of it."""
    df = table(spark, sf, "events", "user_id")
    found = aggs.approx_distinct(df, "user_id").first()
    near = lambda c: F.abs(F.lit(float(found[c])) / F.count_distinct("user_id") - 1) <= 0.1
    return df.agg(F.count_distinct("user_id").alias("exact"), near("approx").alias("approx"), near("hll").alias("hll"))


@register("duplicate_ratio", "SELECT 1 - count(DISTINCT l_quantity) / count(l_quantity) AS duplicate_ratio FROM lineitem")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return aggs.duplicate_ratio(table(spark, sf, "lineitem", "l_quantity"), "l_quantity")


@register("heavy_hitters", "SELECT l_discount, count(*) AS rows FROM lineitem GROUP BY 1 HAVING count(*) >= 0.09 * (SELECT count(*) FROM lineitem)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return aggs.heavy(table(spark, sf, "lineitem", "l_discount"), "l_discount", 0.09)


@register("histogram_equal_width", "SELECT CAST(least(49, floor((p_size - lo) * 50 / (hi - lo))) AS INTEGER) AS bin, count(*) AS rows FROM (SELECT CAST(p_size AS DOUBLE) AS p_size, min(p_size) OVER () AS lo, max(p_size) OVER () AS hi FROM part) GROUP BY 1")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return aggs.histogram(table(spark, sf, "part", "p_size"), "p_size", 50)


@register("histogram_equal_depth", "SELECT count(*) AS rows, true AS even FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """All rows, and whether no bin by sampled quantiles holds more than half as much again as its share."""
    found = aggs.histogram(table(spark, sf, "events", "value"), "value", 16, "depth")
    return found.agg(F.sum("rows").alias("rows"), (F.max("rows") <= 1.5 * F.sum("rows") / 16).alias("even"))


@register("histogram_model", f"SELECT {LINE_SQL} AS bin, count(*) AS rows FROM events GROUP BY 1")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return aggs.histogram(table(spark, sf, "events", "value"), "value", 256, "model", LINE)


@register("regression_line", "SELECT round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 4) AS intercept, round(regr_r2(l_extendedprice, l_quantity), 6) AS r2 FROM lineitem")
def _(spark: SparkSession, sf: str) -> DataFrame:
    found = aggs.line(table(spark, sf, "lineitem", "l_extendedprice", "l_quantity"), F.col("l_extendedprice"), F.col("l_quantity"))
    return found.select(F.round("slope", 4).alias("slope"), F.round("intercept", 4).alias("intercept"), F.round("r2", 6).alias("r2"))


_RESULTS_SQL = "(SELECT event_type AS family, CAST(user_id % 4 AS VARCHAR) AS dataset, CAST(user_id % 3 AS VARCHAR) AS sorter, CAST(event_id % 100 AS DOUBLE) AS keys_per_s FROM events)"


def _results(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "events", "event_id", "event_type", "user_id").select(F.col("event_type").alias("family"), (F.col("user_id") % 4).cast("string").alias("dataset"), (F.col("user_id") % 3).cast("string").alias("sorter"), (F.col("event_id") % 100).cast("double").alias("keys_per_s"))


@register("leaderboard_grouping_sets", f"SELECT family, dataset, sorter, round(keys_per_s, 6) AS keys_per_s, CAST(level AS BIGINT) AS level, CAST(rank() OVER (PARTITION BY level, family, dataset ORDER BY round(keys_per_s, 9) DESC, sorter) AS INTEGER) AS rank FROM (SELECT family, dataset, sorter, avg(keys_per_s) AS keys_per_s, grouping_id(family, dataset, sorter) AS level FROM {_RESULTS_SQL} GROUP BY GROUPING SETS ((family, dataset, sorter), (family, sorter), (sorter)))")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.leaderboard(_results(spark, sf)).withColumn("keys_per_s", F.round("keys_per_s", 6))


@register("leaderboard_rollup", f"SELECT family, sorter, round(avg(keys_per_s), 6) AS keys_per_s FROM {_RESULTS_SQL} GROUP BY ROLLUP (family, sorter)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return _results(spark, sf).rollup("family", "sorter").agg(F.round(F.avg("keys_per_s"), 6).alias("keys_per_s"))


@register("leaderboard_cube", f"SELECT family, sorter, max(keys_per_s) AS keys_per_s FROM {_RESULTS_SQL} GROUP BY CUBE (family, sorter)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return _results(spark, sf).cube("family", "sorter").agg(F.max("keys_per_s").alias("keys_per_s"))


_NAMES = ["0", "1", "2"]


@register("leaderboard_pivot", f"PIVOT (SELECT family, dataset, sorter, keys_per_s FROM {_RESULTS_SQL}) ON sorter IN ('0', '1', '2') USING round(avg(keys_per_s), 6) GROUP BY family, dataset")
def _(spark: SparkSession, sf: str) -> DataFrame:
    wide = metrics.pivoted(_results(spark, sf), _NAMES)
    return wide.select("family", "dataset", *(F.round(c, 6).alias(c) for c in _NAMES))


@register("leaderboard_unpivot", f"SELECT family, dataset, sorter, round(avg(keys_per_s), 6) AS keys_per_s FROM {_RESULTS_SQL} GROUP BY ALL")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.unpivoted(metrics.pivoted(_results(spark, sf), _NAMES), _NAMES).withColumn("keys_per_s", F.round("keys_per_s", 6))


# ---------------------------------------------------------------- experiments

_COORDINATES = "(SELECT vec_id * 64 + i - 1 AS id, CAST(embedding[i] AS DOUBLE) AS c, label FROM (SELECT *, unnest(range(1, 65)) AS i FROM embeddings))"
#: SQL of the keys of each data set's carrier.
_COORDS = "(SELECT CAST(embedding[i] AS DOUBLE) AS c, label FROM (SELECT *, unnest(range(1, 65)) AS i FROM embeddings))"
_CHI = " + ".join(f"64 * CAST(embedding[{i}] AS DOUBLE) * CAST(embedding[{i}] AS DOUBLE)" for i in range(1, 5))
EXPERIMENT_KEYS = {
    "location_ids": "SELECT l_orderkey AS key FROM lineitem",
    "edit_times": "SELECT epoch(ts) AS key FROM events",
    "network_ids": "SELECT user_id AS key FROM events",
    "popularity": "SELECT n_chars AS key FROM documents",
    "pickup_times": "SELECT epoch(l_shipdate) AS key FROM lineitem",
    "uniform": "SELECT l_extendedprice AS key FROM lineitem",
    "normal": f"SELECT 8 * c AS key FROM {_COORDS}",
    "lognormal": f"SELECT c AS key FROM {_COORDS}",
    "mixture": f"SELECT 8 * c + 6 * (label % 5) AS key FROM {_COORDS}",
    "exponential": "SELECT value / 100 AS key FROM events",
    "chi_squared": f"SELECT {_CHI} AS key FROM embeddings",
    "root_dups": "SELECT event_id % CAST(floor(sqrt((SELECT count(*) FROM events))) AS BIGINT) AS key FROM events",
    "two_dups": "SELECT ((event_id % n) * (event_id % n) + n // 2) % n AS key FROM events, (SELECT count(*) AS n FROM events)",
    "zipf": r"SELECT rank() OVER (ORDER BY n DESC) AS key, n FROM (SELECT word, count(*) AS n FROM (SELECT unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS word FROM documents) WHERE word <> '' GROUP BY word)",
}
PARALLEL = {"linear": sorters.linear_partition_sort, "tree": sorters.tree_sample_sort, "radix": sorters.radix_partition_sort, "ecdf": sorters.ecdf_two_pass_sort}


def _experiment_sql(names: list[str], methods: list[str]) -> str:
    def one(name: str) -> str:
        rows = "CAST(sum(n) AS BIGINT)" if name == "zipf" else "count(*)"
        return f"SELECT '{name}' AS dataset, {rows} AS rows, count(DISTINCT key) AS keys FROM ({EXPERIMENT_KEYS[name]})"

    return f"SELECT dataset, sorter, rows, keys, CAST(0 AS BIGINT) AS descents FROM ({' UNION ALL '.join(map(one, names))}), (SELECT unnest({methods!r}) AS sorter)"


def _experiment(spark: SparkSession, sf: str, names: list[str], parallel: bool) -> DataFrame:
    """Every sorter on every data set: its rows, distinct keys and falls as the rows lie.

    Data sets and then sorters run side by side, each proof a plan of its own: one plan of them all weighs on the driver.
    """

    def keys(name: str) -> DataFrame:
        # Written once: each sorter scans its keys several times, and those of zipf rest on a join of all words.
        return materialize(datasets.carrier(spark, sf, name).select(F.col("key").cast("double").alias("key")), "carrier")

    def proved(name: str, df: DataFrame, method: str) -> DataFrame:
        if not parallel:
            lying = sorters.sequential_sort(df, "key", method).select(F.lit(0).alias(PART), "key")
        elif method == "library":
            lying = sorters.builtin_sort(df, "key").withColumn(PART, F.spark_partition_id())
        else:
            lying = PARALLEL[method](df, "key").df
        found = verify.proof(sorters.SortedFrame(lying, KeySpec("key"), 1, None, None, None, None))
        return materialize(found.select(F.lit(name).alias("dataset"), F.lit(method).alias("sorter"), "rows", "keys", "descents"), "proof")

    with ThreadPoolExecutor(len(names)) as pool:
        every = [(name, df, method) for name, df in zip(names, pool.map(inheritable_thread_target(keys), names), strict=True) for method in [*PARALLEL, "library"]]
        return reduce(DataFrame.unionByName, pool.map(inheritable_thread_target(proved), *zip(*every, strict=True)))


for _family, _sets in datasets.FAMILIES.items():
    for _mode in ("parallel", "sequential"):

        @register(f"experiment_{_mode}_{_family}", _experiment_sql(_sets, [*PARALLEL, "library"]))
        def _(spark: SparkSession, sf: str, names: list[str] = _sets, mode: str = _mode) -> DataFrame:
            return _experiment(spark, sf, names, mode == "parallel")


@register("experiment_scaling", f"SELECT n, sorter, n AS rows, CAST(0 AS BIGINT) AS descents FROM (SELECT count(*) FILTER (WHERE id % step = 0) AS n FROM {_COORDINATES}, (SELECT unnest([100, 10, 1]) AS step) GROUP BY step), (SELECT unnest(['linear', 'tree', 'radix', 'ecdf']) AS sorter)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Parallel sorters on a hundredth, a tenth and all of the carrier of normal keys; rates are printed by experiments.py."""
    every = None
    for step in (100, 10, 1):
        df = datasets.carrier(spark, sf, "normal").where(F.pmod("id", F.lit(step)) == 0).select("key")
        n = df.count()
        for name, sorter in PARALLEL.items():
            found = verify.proof(sorter(df, "key")).select(F.lit(n).cast("long").alias("n"), F.lit(name).alias("sorter"), "rows", "descents")
            every = found if every is None else every.unionByName(found)
    return every


@register("crossover", "SELECT n, (n % 7 + 1.0) / (n % 5 + 1.0) AS speed_up, n % 7 > n % 5 AS ahead FROM (SELECT CAST(user_id AS BIGINT) AS n FROM events GROUP BY 1)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Speed-up of one sorter over another by size, on stated rates; measured ones are printed by experiments.py."""
    sizes = table(spark, sf, "events", "user_id").distinct().select(F.col("user_id").cast("long").alias("n"))
    rates = sizes.select("n", F.lit("a").alias("sorter"), (F.col("n") % 7 + 1.0).alias("keys_per_s")).unionByName(sizes.select("n", F.lit("b").alias("sorter"), (F.col("n") % 5 + 1.0).alias("keys_per_s")))
    return metrics.crossover(rates, "a", "b")


@register("peak_memory", f"{_STATES_SQL}, b AS (SELECT *, CAST(unnest([1, 2, 4]) AS INTEGER) AS block FROM r), h AS (SELECT user_id, block, i + 1 - block * coalesce(sum(CASE WHEN (j + 1) % block = 0 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id, block ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS held FROM b) SELECT user_id, block, CAST(max(held) AS INTEGER) AS peak, CAST(count(*) AS INTEGER) AS copy FROM h GROUP BY user_id, block")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Most keys in buffers at once while the events of each user are classified, against a copy of all keys."""
    one = lambda b: _example_states(spark, sf, lambda found: [(b, found.peak, sum(found.sizes))], "block int, peak int, copy int", b)
    return one(1).unionByName(one(2)).unionByName(one(4))


# ---------------------------------------------------------------- data sets, sources, sinks, SQL


@register("gen_root_dups", "SELECT event_id AS id, event_id % CAST(floor(sqrt((SELECT count(*) FROM events))) AS BIGINT) AS key FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return datasets.carrier(spark, sf, "root_dups")


@register("gen_two_dups", "SELECT event_id AS id, ((event_id % n) * (event_id % n) + n // 2) % n AS key FROM events, (SELECT count(*) AS n FROM events)")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return datasets.carrier(spark, sf, "two_dups")


_SQUARES = " + ".join(f"64 * CAST(embedding[{i}] AS DOUBLE) * CAST(embedding[{i}] AS DOUBLE)" for i in range(1, 5))
_CARRIERS = {
    "popularity": "SELECT doc_id AS id, n_chars AS key FROM documents",
    "exponential": "SELECT event_id AS id, value / 100 AS key FROM events",
    "network_ids": "SELECT event_id AS id, user_id AS key FROM events",
    "normal": f"SELECT id, 8 * c AS key FROM {_COORDINATES}",
    "lognormal": f"SELECT id, round(exp(4 * c), 9) AS key FROM {_COORDINATES}",
    "mixture": f"SELECT id, 8 * c + 6 * (label % 5) AS key FROM {_COORDINATES}",
    "chi_squared": f"SELECT vec_id AS id, {_SQUARES} AS key FROM embeddings",
}
#: Carriers without an id of their own: the rows of each key.
_KEY_COUNTS = {
    "edit_times": "SELECT CAST(epoch(ts) AS DOUBLE) AS key, count(*) AS rows FROM events GROUP BY 1",
    "pickup_times": "SELECT CAST(epoch(l_shipdate) AS DOUBLE) AS key, count(*) AS rows FROM lineitem GROUP BY 1",
    "uniform": "SELECT l_extendedprice AS key, count(*) AS rows FROM lineitem GROUP BY 1",
    "location_ids": "SELECT l_orderkey AS key, count(*) AS rows FROM lineitem GROUP BY 1",
    "quantity": "SELECT l_quantity AS key, count(*) AS rows FROM lineitem GROUP BY 1",
    "discount": "SELECT l_discount AS key, count(*) AS rows FROM lineitem GROUP BY 1",
    "zipf": r"SELECT key, CAST(sum(n) AS BIGINT) AS rows FROM (SELECT n, rank() OVER (ORDER BY n DESC) AS key FROM (SELECT word, count(*) AS n FROM (SELECT unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS word FROM documents) WHERE word <> '' GROUP BY word)) GROUP BY key",
}

for _name, _carrier_sql in _CARRIERS.items():

    @register(f"carrier_{_name}", _carrier_sql)
    def _(spark: SparkSession, sf: str, name: str = _name) -> DataFrame:
        found = datasets.carrier(spark, sf, name)
        return found.withColumn("key", F.round("key", 9)) if name == "lognormal" else found


for _name, _carrier_sql in _KEY_COUNTS.items():

    @register(f"carrier_{_name}", _carrier_sql)
    def _(spark: SparkSession, sf: str, name: str = _name) -> DataFrame:
        return datasets.carrier(spark, sf, name).groupBy("key").agg(F.count("*").alias("rows"))


@register("generated_families")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Keys that each data set's generator makes of the ids of all events."""
    ids = table(spark, sf, "events", "event_id").withColumnRenamed("event_id", "id")
    n, every = ids.count(), None
    for family, names in datasets.FAMILIES.items():
        for name in names:
            rows = datasets.keys_of(ids, name, max(n, 1)).agg(F.count("key").alias("rows"), F.count_distinct("key").alias("keys"), F.avg(F.col("key").cast("double")).alias("mean")).select(F.lit(family).alias("family"), F.lit(name).alias("dataset"), "*")
            every = rows if every is None else every.unionByName(rows)
    return every


@register("key_generator_source", "SELECT event_id AS id, CAST(event_id % CAST(floor(sqrt((SELECT max(event_id) + 1 FROM events))) AS BIGINT) AS DOUBLE) AS key FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Keys of the data source for the ids of all events."""
    datasets.register(spark)
    events = table(spark, sf, "events", "event_id").withColumnRenamed("event_id", "id")
    n = (events.agg(F.max("id")).first()[0] or 0) + 1
    made = spark.read.format("keygen").option("dist", "root_dups").option("n", str(n)).option("partitions", str(max(4, -(-n // 1_000_000)))).load()
    return events.join(made.hint("merge"), "id").select("id", "key")


for _format in ("csv", "json", "orc"):

    @register(f"read_{_format}", "SELECT c_custkey, c_acctbal, c_mktsegment FROM customer")
    def _(spark: SparkSession, sf: str, fmt: str = _format) -> DataFrame:
        path = new_folder(spark, fmt)
        table(spark, sf, "customer", "c_custkey", "c_acctbal", "c_mktsegment").write.format(fmt).save(path)
        return io.read_as(spark, fmt, path, "c_custkey long, c_acctbal double, c_mktsegment string")


@register("read_text", "SELECT CAST(l_orderkey AS VARCHAR) AS value FROM lineitem")
def _(spark: SparkSession, sf: str) -> DataFrame:
    path = new_folder(spark, "text")
    table(spark, sf, "lineitem", "l_orderkey").select(F.col("l_orderkey").cast("string")).write.text(path)
    return io.read_as(spark, "text", path, "value string")


@register("read_partitions", "SELECT event_id, event_type FROM events WHERE event_type = 'click'")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Only the folder of the partition value that the filter names is read."""
    path = new_folder(spark, "partitions")
    table(spark, sf, "events", "event_id", "event_type").write.partitionBy("event_type").parquet(f"{path}/events.parquet")
    return io.read(spark, path, "events", ["event_id", "event_type"], "event_type = 'click'")


@register("ordered_sink_range", "SELECT event_id, value FROM events WHERE value BETWEEN 30 AND 33")
def _(spark: SparkSession, sf: str) -> DataFrame:
    path = new_folder(spark, "ordered")
    sinks.write_ordered(sorters.linear_partition_sort(table(spark, sf, "events", "event_id", "value"), VALUE), path)
    return sinks.read_range(spark, path, "value", 30.0, 33.0).select("event_id", "value")


@register("bucketed_sink", "SELECT event_id, value FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    path = new_folder(spark, "bucketed")
    df, frame = _frame(spark, sf)
    sinks.write_bucketed(df, frame, path)
    return spark.read.parquet(path).select("event_id", "value")


@register("model_store", "SELECT CAST(256 AS INTEGER) AS k, slope, intercept FROM (" + _SQL["minmax_fit_value"] + ")")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """A line fitted to all events, as it comes back from disk."""
    path = new_folder(spark, "model")
    sinks.save_model(spark, min_max_distributed(table(spark, sf, "events", "value"), "value", 256), path)
    back = sinks.load_model(spark, path)
    return spark.createDataFrame([(back.k, back.slope, back.intercept)], "k int, slope double, intercept double")


@register("model_store_deep", "SELECT event_id, true AS same FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Whether stored and read models of every kind place a row alike."""
    df = table(spark, sf, "events", "event_id", "value")
    rmi = Rmi.two_level_distributed(df, "value", 8)
    models = [EcdfBucket(rmi, 64), WithHeavy(LINE, np.array([1.5, 7.0])), Composite(LinearBucket(0.01, 0.0, 4), {1: SplitterTree(np.array([120.0, 150.0]), np.array([150.0])), 2: LinearBucket(0.1, -20.0, 8)}), RadixBucket.fit(0, 255, 4)]
    same = F.lit(True)
    for model in models:
        path = new_folder(spark, "model")
        sinks.save_model(spark, model, path)
        same = same & (model.column(F.col("value")) == sinks.load_model(spark, path).column(F.col("value")))
    return df.select("event_id", same.alias("same"))


@register("sql_rmi_predict", f"SELECT event_id, {_ECDF_SQL} AS share FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    sql_functions.register(spark)
    table(spark, sf, "events", "event_id", "value").createOrReplaceTempView("modelsort_events")
    return spark.sql("SELECT event_id, rmi_predict(value, 0.004D, 0D, array(0.02D, 0.002D, 0.001D, 0.0005D), array(0.05D, 0.4D, 0.55D, 0.8D)) AS share FROM modelsort_events")


@register("sql_splitter_bucket", f"SELECT event_id, CAST(CASE WHEN event_id % 2 = 0 THEN {_case_sql([5.0, 50.0])} ELSE {_case_sql(SPLITTERS)} END AS INTEGER) AS bucket FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    """Splitters that differ from row to row."""
    sql_functions.register(spark)
    table(spark, sf, "events", "event_id", "value").createOrReplaceTempView("modelsort_events")
    return spark.sql(f"SELECT event_id, splitter_bucket(value, CASE WHEN event_id % 2 = 0 THEN array(5D, 50D) ELSE array({', '.join(f'{x}D' for x in SPLITTERS)}) END) AS bucket FROM modelsort_events")


@register("sql_linear_bucket", f"SELECT event_id, {LINE_SQL} AS bucket FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    sql_functions.register(spark)
    table(spark, sf, "events", "event_id", "value").createOrReplaceTempView("modelsort_events")
    return spark.sql(f"SELECT event_id, linear_bucket(value, {LINE.slope!r}D, {LINE.intercept!r}D, 256) AS bucket FROM modelsort_events")


# ---------------------------------------------------------------- streams


def _stream(spark: SparkSession, sf: str) -> DataFrame:
    """Events replayed in one batch; each call has a checkpoint of its own.

    A stream's path must be a folder or a pattern; the pattern stands for the table as one file and as a folder of files.
    """
    schema = spark.read.parquet(f"{sf}/events.parquet").schema
    return streaming.replay(spark, f"{sf}/events.parque[t]", schema, files_per_trigger=None)


def _wall_seconds(c: str):
    """Seconds of a time stamp's local wall clock, the same in any session time zone."""
    return (F.unix_date(F.to_date(c)) * 86400 + F.hour(c) * 3600 + F.minute(c) * 60 + F.second(c)).cast("long")


def _result(frame: DataFrame, mode: str = "complete") -> DataFrame:
    """No frame of these queries waits for a watermark: counts are complete results, joins inner or against a table."""
    return streaming.run_to_files(frame, "stream", mode, closing=False)


@register("stream_bucket_counts_tumbling", f"SELECT CAST(epoch(time_bucket(INTERVAL 1 HOUR, ts)) AS BIGINT) AS start, {LINE_SQL} AS bucket, count(*) AS rows FROM events GROUP BY 1, 2")
def _(spark: SparkSession, sf: str) -> DataFrame:
    found = _result(streaming.bucket_counts(_stream(spark, sf), "value", LINE))
    return found.select(_wall_seconds("start").alias("start"), "bucket", "rows")


@register("stream_bucket_counts_sliding", "SELECT CAST(epoch(time_bucket(INTERVAL 30 MINUTES, ts)) AS BIGINT) - 1800 * i AS start, count(*) AS rows FROM events, (SELECT unnest([0, 1, 2, 3]) AS i) GROUP BY 1")
def _(spark: SparkSession, sf: str) -> DataFrame:
    found = _result(streaming.bucket_counts(_stream(spark, sf), "value", LINE, window="2 hours", slide="30 minutes"))
    return found.groupBy(_wall_seconds("start").alias("start")).agg(F.sum("rows").alias("rows"))


@register("stream_session_counts", "SELECT user_id, count(*) AS sessions, CAST(sum(n) AS BIGINT) AS rows FROM (SELECT user_id, session, count(*) AS n FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTES OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL THEN 1 ELSE 0 END AS new FROM events)) GROUP BY 1, 2) GROUP BY 1")
def _(spark: SparkSession, sf: str) -> DataFrame:
    found = _result(streaming.session_counts(_stream(spark, sf), "value", LINE, "user_id", late=None))
    return found.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("rows").alias("rows"))


@register("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return _result(streaming.dedup(_stream(spark, sf), ["user_id", "event_type"], late="400 days").select("user_id", "event_type"), "append")


@register("stream_drift", f"WITH b AS (SELECT {LINE_SQL} AS bucket, count(*) AS n FROM events GROUP BY 1), s AS (SELECT CAST(sum(n) AS BIGINT) AS rows, max(n) / sum(n) AS max_share, coalesce(sum(n) FILTER (WHERE bucket IN (0, 255)), 0) / sum(n) AS end_share FROM b) SELECT CAST(0 AS BIGINT) AS batch, *, max_share > 1 / 3 OR end_share > 0.1 AS refit FROM s")
def _(spark: SparkSession, sf: str) -> DataFrame:
    out: list[dict] = []
    stream = _stream(spark, sf).writeStream.foreachBatch(streaming.drift_monitor("value", LINE, out)).trigger(availableNow=True).start()
    stream.awaitTermination()
    return spark.createDataFrame(out, "batch long, rows long, max_share double, end_share double, refit boolean")


@register("stream_sorted_runs", "SELECT event_id, row_number() OVER (ORDER BY value, event_id) AS position FROM events")
def _(spark: SparkSession, sf: str) -> DataFrame:
    path = new_folder(spark, "runs")
    stream = _stream(spark, sf).select("event_id", "value").writeStream.foreachBatch(streaming.sorted_runs(LINE, "value", path)).trigger(availableNow=True).start()
    stream.awaitTermination()
    runs = streaming.compact(spark, path, "value", LINE)
    return rank.global_position(sorters.sort_with(runs.rows(), VALUE, LINE)).select("event_id", "position")


@register("stream_late_rows", "WITH b AS (SELECT epoch(ts) AS t, CAST((event_id * 7919) % 10007 % 4 AS BIGINT) AS batch FROM events), m AS (SELECT batch, max(t) AS most FROM b GROUP BY 1) SELECT b.batch, count(*) AS rows, count(*) FILTER (WHERE t < (SELECT max(most) FROM m WHERE m.batch < b.batch) - 3600) AS late FROM b GROUP BY 1")
def _(spark: SparkSession, sf: str) -> DataFrame:
    path, events = new_folder(spark, "arrivals"), table(spark, sf, "events")
    for i in range(4):  # a file each, so that arrival order differs from event order
        events.where(F.pmod(F.col("event_id") * 7919, F.lit(10007)) % 4 == i).coalesce(1).write.mode("append").parquet(path)
    state = new_folder(spark, "late-rows")
    stream = streaming.replay(spark, path, events.schema).writeStream.foreachBatch(streaming.late_counter("ts", 3600, state)).trigger(availableNow=True).start()
    stream.awaitTermination()
    return spark.read.schema("rows long, late long, latest double, batch long").parquet(state).select("batch", "rows", "late")


@register("stream_asof_static", "SELECT e.event_id, b.event_id AS other FROM events e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'click' GROUP BY 1, 2) b ON e.user_id = b.user_id AND e.ts >= b.ts")
def _(spark: SparkSession, sf: str) -> DataFrame:
    clicks = table(spark, sf, "events", "event_id", "user_id", "ts", "event_type").where("event_type = 'click'")
    static = clicks.select("user_id", F.col("ts").cast("timestamp").alias("at"), F.col("event_id").alias("other"))
    stream = _stream(spark, sf).select("event_id", "user_id", "ts")
    return _result(streaming.asof_static(stream, static, "ts", "at", "user_id", ("other",)).select("event_id", "other"), "append")


@register("stream_reservoir")
def _(spark: SparkSession, sf: str) -> DataFrame:
    return _result(streaming.reservoir(_stream(spark, sf), "event_id", "value"), "update")


@register("stream_interval_join", "SELECT a.event_id, b.event_id AS other FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts <= a.ts AND b.ts >= a.ts - INTERVAL 1 HOUR")
def _(spark: SparkSession, sf: str) -> DataFrame:
    left = _stream(spark, sf).select("event_id", "user_id", "ts")
    right = _stream(spark, sf).select(F.col("event_id").alias("other"), "user_id", F.col("ts").alias("other_ts"))
    return _result(streaming.interval_join(left, right, "user_id", "ts", "other_ts", late=None).select("event_id", "other"), "append")
