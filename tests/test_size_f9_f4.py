"""Votes and metrics without a joined row for each pair."""

from vecspark.operators import bof
from vecspark.queries.catalog import QUERIES


def test_votes_join_no_objects(spark):
    index = spark.createDataFrame([(1, 0, 2), (1, 1, 1), (2, 0, 3), (3, 1, 4), (4, 2, 7)], "doc_id long, word long, n long")
    votes = bof.bof_vote(index, index.where("doc_id < 3").withColumnRenamed("doc_id", "qid"), 1)
    assert sorted((r["qid"], r["doc_id"], r["votes"]) for r in votes.collect()) == [(1, 2, 6), (2, 1, 6)]
    assert "MapInArrow" in votes._jdf.queryExecution().optimizedPlan().toString()


def test_metrics_make_pairs_in_the_tasks(spark, sf):
    plan = QUERIES["q_metrics"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoopJoin" not in plan and "CartesianProduct" not in plan
