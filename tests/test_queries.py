"""Catalogue queries against their DuckDB SQL on the smallest tables."""

import numbers

import duckdb
import pytest

from modelsort import catalog

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    return con


def rows(frame):
    import math

    clean = lambda v: None if v is None or (isinstance(v, float) and math.isnan(v)) or str(v) == "<NA>" else (round(float(v), 6) if isinstance(v, numbers.Number) and not isinstance(v, bool) else str(v))
    return sorted((tuple(clean(v) for v in r) for r in frame[sorted(frame.columns)].itertuples(index=False)), key=str)


@pytest.mark.parametrize("name", catalog.oracle_sql())
def test_query_equals_sql(spark, duck, name):
    found = catalog.queries()[name](spark, DATA).toPandas()
    wanted = duck.execute(catalog.oracle_sql()[name]).df()
    assert sorted(found.columns) == sorted(wanted.columns)
    assert rows(found) == rows(wanted)


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 1000
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
