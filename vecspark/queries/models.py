"""Models that many queries share, trained once a process for each table folder."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecspark.operators import codebook
from vecspark.operators.index import IvfIndex, MultiIndex
from vecspark.operators.projection import fixed_rotation, rotate_fixed
from vecspark.sources import tables as T

_KEPT: dict = {}


def once(spark: SparkSession, key: tuple, make):
    key = (spark.sparkContext.applicationId, *key)
    if key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT[key]


def v0(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    return T.split(T.vectors_embeddings(spark, sf))


def v0_rotated(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """V0 under a fixed rotation in fixed point, which two engines compute alike."""
    return T.split(once(spark, (sf, "v0r"), lambda: rotate_fixed(T.vectors_embeddings(spark, sf), fixed_rotation(64, 5)).persist()))


def v1(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    return T.split(once(spark, (sf, "v1"), lambda: T.vectors_lineitem(spark, sf).persist()))


def v1_training(spark: SparkSession, sf: str, modulus: int = 101) -> DataFrame:
    return v1(spark, sf)[1].where(F.pmod("vec_id", F.lit(modulus)) == 0)


def pq0(spark: SparkSession, sf: str, m: int, k: int, iters: int = 3):
    return once(spark, (sf, "pq0", m, k, iters), lambda: codebook.train_pq(v0(spark, sf)[1], m, int(np.log2(k)), iters, k))


def pq1(spark: SparkSession, sf: str, m: int, k: int, iters: int = 1):
    return once(spark, (sf, "pq1", m, k, iters), lambda: codebook.train_pq(v1_training(spark, sf), m, int(np.log2(k)), iters, k))


def ivf0(spark: SparkSession, sf: str, k: int = 8, m: int = 8, b: int = 4, iters: int = 3, residual: bool = True):
    return once(spark, (sf, "ivf0", k, m, b, iters, residual), lambda: IvfIndex.build(v0(spark, sf)[1], k, m, b, iters, residual))


def ivf1(spark: SparkSession, sf: str, k: int = 8, m: int = 8, b: int = 8, iters: int = 1):
    return once(spark, (sf, "ivf1", k, m, b, iters), lambda: IvfIndex.build(v1_training(spark, sf), k, m, b, iters))


def imi0(spark: SparkSession, sf: str, k: int = 4, m: int = 8, b: int = 4, iters: int = 3):
    return once(spark, (sf, "imi0", k, m, b, iters), lambda: MultiIndex.build(v0(spark, sf)[1], k, m, b, iters))


def nested0(spark: SparkSession, sf: str, m: int = 4, b: int = 8, b_coarse: int = 4, numbering: str = "ntile", iters: int = 3, rotated: bool = False):
    def make():
        fine = codebook.train_pq(v0_rotated(spark, sf)[1], m, b, iters) if rotated else pq0(spark, sf, m, 1 << b, iters)
        return codebook.nest(fine, b_coarse, numbering)

    return once(spark, (sf, "nested0", m, b, b_coarse, numbering, iters, rotated), make)
