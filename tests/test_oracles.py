"""Registered queries against DuckDB on the smallest tables (a fast selection; all at sf0.01 by tools/parity.py)."""

import duckdb
import pytest

from vecspark.queries.catalog import ORACLES, QUERIES
from vecspark.sources.tables import TABLES

FAST = [
    "q_bruteforce_knn", "q_pq_codebook", "q_pq_encode", "q_adc_topk", "q_adc_packed", "q_adc_vertical", "q_adc_gather", "q_ivf_search", "q_imi_sequence", "q_imi_search", "q_bounded_topk", "q_bounded_kernel", "q_bounded_renumbered",
    "q_bounded_pruned", "q_bounded_equals_adc", "q_nibble_topk", "q_nibble_kernel_x2", "q_nested_topk", "q_nested_eager", "q_capped_kernel", "q_kdtree_exact", "q_kdtree_priority", "q_kmtree_priority", "q_lookup_cost", "q_memory_model", "q_group_memory",
    "q_small_table_plan", "q_aq_distance", "q_cq_distance", "o_range_join", "o_asof_join", "o_list_rollup", "o_grouping_sets", "s_tumbling", "s_dedup", "u_components_udtf", "w_scan_variants", "w_nn_classifier",
]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def rows(frame, columns):
    return sorted(repr([None if v != v else v for v in r]) for r in frame[columns].astype(object).values.tolist())


@pytest.mark.parametrize("name", FAST)
def test_matches_oracle(spark, sf, duck, name):
    got, want = QUERIES[name](spark, sf).toPandas(), duck.execute(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got, sorted(got.columns)) == rows(want, sorted(got.columns))


def test_every_oracle_has_a_query():
    assert set(ORACLES) <= set(QUERIES)
