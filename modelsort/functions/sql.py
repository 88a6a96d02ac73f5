"""Functions for SQL text: bucket lines as inlined SQL, splitter search and key bits as Arrow functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from modelsort.functions.keys import order_bits_np
from modelsort.operators.blocks import BlockTrace


def register(spark: SparkSession) -> None:
    """Register ``linear_bucket``, ``rmi_predict`` (two levels), ``order_bits``, ``splitter_bucket`` and the table function ``block_trace``."""
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION linear_bucket(x DOUBLE, a DOUBLE, b DOUBLE, k INT) RETURNS INT "
        "RETURN CAST(floor(least(CAST(k - 1 AS DOUBLE), greatest(0D, a * x + b))) AS INT)"
    )

    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION rmi_predict(x DOUBLE, root_a DOUBLE, root_b DOUBLE, a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE "
        "RETURN least(0.9999999999999999D, greatest(0D, a[CAST(floor(least(0.9999999999999999D, greatest(0D, root_a * x + root_b)) * size(a)) AS INT)] * x "
        "+ b[CAST(floor(least(0.9999999999999999D, greatest(0D, root_a * x + root_b)) * size(a)) AS INT)]))"
    )

    def bits(values: pa.Array) -> pa.Array:
        mask = values.is_null().to_numpy(zero_copy_only=False)
        return pa.array(order_bits_np(values.fill_null(0.0).to_numpy(zero_copy_only=False).astype(float)), pa.int64(), mask=mask)

    def search(values: pa.Array, splitters: pa.Array) -> pa.Array:
        # Splitters may differ by row: each run of equal arrays is searched at once.
        lists = splitters.to_pylist()
        x = values.to_numpy(zero_copy_only=False).astype(float)
        out, start = np.zeros(len(x), np.int32), 0
        for stop in range(1, len(lists) + 1):
            if stop == len(lists) or lists[stop] != lists[start]:
                out[start:stop] = np.searchsorted(np.array(lists[start] or [], float), x[start:stop], "left")
                start = stop
        return pa.array(out, mask=values.is_null().to_numpy(zero_copy_only=False) | splitters.is_null().to_numpy(zero_copy_only=False))

    bits.__annotations__ = {"values": pa.Array, "return": pa.Array}
    search.__annotations__ = {"values": pa.Array, "splitters": pa.Array, "return": pa.Array}
    spark.udf.register("order_bits", F.arrow_udf(bits, "long"))
    spark.udf.register("splitter_bucket", F.arrow_udf(search, "int"))
    spark.udtf.register("block_trace", BlockTrace)
