"""Cost models read the given vectors."""

import pytest

from vecspark.queries.catalog import QUERIES


@pytest.mark.parametrize("name", ["q_group_memory", "q_lookup_cost", "q_memory_model", "q_small_table_plan", "q_two_codes_memory"])
def test_cost_models_scan_the_vectors(spark, sf, name):
    frame = QUERIES[name](spark, sf)
    plan = frame._jdf.queryExecution().executedPlan().toString()
    assert "FileScan parquet [embedding" in plan and frame.count() > 0
