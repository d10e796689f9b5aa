"""Exact distances by matrix products against all pairs."""

from pyspark.sql import functions as F

from vecspark.functions.ranking import top_k
from vecspark.operators import exact
from vecspark.queries import core, models


def test_products_equal_all_pairs(spark, sf, monkeypatch):
    q, b = models.v0(spark, sf)
    pairs = core.exact(q, b, 64).cache()
    for others in (False, True):
        want = top_k(pairs.where("qid <> vec_id") if others else pairs, 7, ["qid"], ["dist", "vec_id"]).select("qid", "rk", "vec_id", "dist")
        got = exact.nearest_rows(q, b.repartition(3), 7, others)
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    near = exact.rows_within(q, b, 22_000_000)
    assert sorted(map(tuple, near.collect())) == sorted(map(tuple, pairs.where("dist <= 22000000").select("qid", "vec_id", "dist").collect()))
    counts = exact.counts_within(q, b, 26_000_000)
    assert sorted(map(tuple, counts.select("qid", "inside").collect())) == sorted(map(tuple, pairs.where("dist <= 26000000").groupBy("qid").agg(F.count("*")).collect()))


def test_queries_make_no_row_for_each_pair(spark, sf):
    from vecspark.queries.catalog import QUERIES

    for name in ("q_radius", "q_radius_equals_knn", "o_theta_radius_join"):
        plan = QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoopJoin" not in plan and "CartesianProduct" not in plan, name
