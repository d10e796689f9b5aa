"""Accuracy measures: ground truth, recall, candidate recall, approximation ratio."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecspark.operators.exact import nearest_rows


def ground_truth(queries: DataFrame, base: DataFrame, d: int) -> DataFrame:
    """(qid, truth): the exact nearest neighbour other than the query's own row."""
    return nearest_rows(queries, base, 1, others=True).select("qid", F.col("vec_id").alias("truth"))


def recall_at(result: DataFrame, truth: DataFrame, grid: tuple[int, ...]) -> DataFrame:
    """(r, hits, queries, recall): share of queries whose true neighbour is among the first r, the
    query's own row not counted."""
    others = result.where("vec_id <> qid").withColumn("rk", F.row_number().over(W.partitionBy("qid").orderBy("rk")))
    found = truth.join(others.select("qid", F.col("vec_id").alias("truth"), "rk"), ["qid", "truth"], "left")
    spread = found.withColumn("r", F.explode(F.array(*[F.lit(r).cast("long") for r in grid])))
    out = spread.groupBy("r").agg(F.count_if(F.col("rk") <= F.col("r")).alias("hits"), F.count("*").alias("queries"))
    return out.withColumn("recall", F.round(F.col("hits") / F.col("queries"), 6))


def candidate_recall(candidates: DataFrame, truth: DataFrame) -> DataFrame:
    """(queries, hits, recall) of a candidate set (qid, vec_id)."""
    found = truth.join(candidates.select("qid", F.col("vec_id").alias("truth"), F.lit(1).alias("hit")), ["qid", "truth"], "left")
    return found.agg(F.count("*").alias("queries"), F.count("hit").alias("hits")).withColumn("recall", F.round(F.col("hits") / F.col("queries"), 6))


def approximation(result: DataFrame, exact: DataFrame) -> DataFrame:
    """(qid, rk, ratio): found over true distance at each rank, of plain (not squared) distances."""
    return result.join(exact.select("qid", "rk", F.col("dist").alias("true")), ["qid", "rk"]).withColumn("ratio", F.round(F.sqrt(F.col("dist").cast("double")) / F.sqrt(F.greatest("true", F.lit(1)).cast("double")), 6)).select("qid", "rk", "ratio")
