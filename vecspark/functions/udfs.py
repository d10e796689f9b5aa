"""SQL surface: Arrow functions, aggregates and table functions over the kernels."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecspark.operators.codebook import PQModel


def encode_udf(model: PQModel):
    """array -> array of codes."""

    @F.pandas_udf("array<long>")
    def encode(e: pd.Series) -> pd.Series:
        return pd.Series(list(model.encode(np.array(e.tolist(), float))))

    return encode


def adc_udf(model: PQModel, tables: dict[int, np.ndarray]):
    """(array of codes, query) -> table-sum distance under that query's tables."""

    @F.pandas_udf("long")
    def distance(c: pd.Series, qid: pd.Series) -> pd.Series:
        codes, out = np.array(c.tolist()), np.zeros(len(c), np.int64)
        for q in qid.unique():
            own = np.flatnonzero(qid.to_numpy() == q)
            out[own] = tables[q][np.arange(model.m), codes[own]].sum(axis=1)
        return pd.Series(out)

    return distance


@F.pandas_udf(T.ArrayType(T.LongType()))
def vector_mean(e: pd.Series) -> list:
    """Grouped aggregate: floored component means."""
    return np.floor(np.array(e.tolist(), float).mean(axis=0)).astype(int).tolist()


@F.udtf(returnType=T.StructType([T.StructField("pos", T.IntegerType()), T.StructField("x", T.LongType())]))
class Components:
    """Table function: one row for each component of a vector."""

    def eval(self, e):
        for i, x in enumerate(e or ()):
            yield i, x


def register(spark: SparkSession) -> None:
    spark.udtf.register("vector_components", Components)
    spark.udf.register("vector_mean", vector_mean)
