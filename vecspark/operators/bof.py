"""Bag of features: objects of many vectors, indexed by visual words, matched by votes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.functions.ranking import top_k
from vecspark.operators.encode import assign
from vecspark.operators.exact import greatest_products, items_of, profiles


def bof_index(descriptors: DataFrame, words: np.ndarray, entity: str = "doc_id") -> DataFrame:
    """(entity, e) -> (entity, word, n): how often a word occurs in an object."""
    return assign(descriptors, words, entity, "word").groupBy(entity, "word").agg(F.count("*").alias("n"))


def bof_vote(index: DataFrame, queries: DataFrame, k: int, entity: str = "doc_id", idf: bool = False, objects: int | None = None) -> DataFrame:
    """(qid, rk, entity, votes): objects by matching (line, query line) pairs, optionally idf-weighted.

    Words are counted per object, so that votes are products of two objects' counts. With weights, which are no
    integers, objects are joined by words instead.
    """
    if not idf:
        items = items_of(index, "word")
        near = greatest_products(profiles(queries, "qid", "word", "n", items), profiles(index.withColumnRenamed(entity, "vec_id"), "vec_id", "word", "n", items), k)
        return near.select("qid", F.col("vec_id").alias(entity), F.col("dot").alias("votes"), "rk")
    joined = index.join(F.broadcast(queries.withColumnRenamed("n", "nq")), "word").where(F.col(entity) != F.col("qid"))
    df = index.groupBy("word").agg(F.count("*").alias("df"))
    joined = joined.join(F.broadcast(df), "word")
    weight = F.log(F.lit(float(objects)) / F.col("df"))
    votes = joined.groupBy("qid", entity).agg(F.sum(F.col("n") * F.col("nq") * weight).alias("votes"))
    return top_k(votes, k, ["qid"], [F.col("votes").desc(), F.col(entity)])
