"""Rows that joins multiply are not broadcast, since a broadcast is gathered on the driver."""

import pytest

from modelsort import catalog

DATA = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["rmi_lookup", "theta_join"])
def test_multiplied_rows_are_not_broadcast(spark, name):
    plan = catalog.queries()[name](spark, DATA)._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastExchange" not in plan and "SortMergeJoin" in plan
