"""Codes of line items are read by few tasks, whatever the shuffles leave."""

import duckdb

from vecspark.operators import packed
from vecspark.queries.catalog import ORACLES, QUERIES


def test_few_rows_take_few_tasks(spark):
    codes = spark.range(3000).withColumnRenamed("id", "vec_id").repartition(64)
    assert packed.dealt(codes).rdd.getNumPartitions() == 3
    assert packed.dealt(codes).count() == 3000
    assert packed.tasks_for(codes, 50 * packed.BLOCK_ROWS) == 50


def test_bounded_scan_of_dealt_codes(spark, sf):
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{sf}/lineitem.parquet'")
    columns = ["qid", "rk", "vec_id", "dist"]
    got = QUERIES["w_bounded_lineitem"](spark, sf).select(*columns).collect()
    want = con.execute(ORACLES["w_bounded_lineitem"]).df()[columns]
    assert sorted(map(tuple, got)) == sorted(map(tuple, want.values.tolist()))
