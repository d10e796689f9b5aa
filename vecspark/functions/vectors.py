"""Vectors as columns: fixed point, validation, distances, sub-vectors.

Two number modes. Production vectors are arrays of floats. The fixed-point mode keeps
``floor(x * 4096)`` as long integers, so that sums do not depend on their order and
two engines agree to the bit.
"""

from __future__ import annotations

from functools import reduce
from operator import add

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SCALE = 4096


def fixed_point(vector: Column, scale: int = SCALE) -> Column:
    return F.transform(vector, lambda x: F.floor(x.cast("double") * scale).cast("long"))


def total(terms: list[Column]) -> Column:
    """An unrolled sum: stays within one generated function, unlike ``aggregate``."""
    return reduce(add, terms)


def l2sq(a: Column, b: Column, d: int) -> Column:
    return total([(a[i] - b[i]) * (a[i] - b[i]) for i in range(d)])


def l1(a: Column, b: Column, d: int) -> Column:
    return total([F.abs(a[i] - b[i]) for i in range(d)])


def dot(a: Column, b: Column, d: int) -> Column:
    return total([a[i] * b[i] for i in range(d)])


def cosine(a: Column, b: Column, d: int) -> Column:
    return dot(a, b, d) / (F.sqrt(dot(a, a, d).cast("double")) * F.sqrt(dot(b, b, d).cast("double")))


def l2_normalize(vector: Column) -> Column:
    norm = F.sqrt(F.aggregate(vector, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
    return F.when(norm > 0, F.transform(vector, lambda x: x.cast("double") / norm)).otherwise(F.transform(vector, lambda x: x.cast("double")))


def validate(frame: DataFrame, d: int, column: str = "e") -> DataFrame:
    """Only rows whose vector has ``d`` numbers, none null or NaN."""
    bad = F.exists(column, lambda x: x.isNull() | F.isnan(x.cast("double")))
    return frame.where(F.col(column).isNotNull() & (F.size(column) == d) & ~F.coalesce(bad, F.lit(True)))


def explode_components(frame: DataFrame, key: str, d: int, m: int, column: str = "e") -> DataFrame:
    """Long form (key, part, dim, x) of m sub-vectors."""
    return frame.select(key, F.posexplode(column).alias("i", "x")).select(key, F.floor(F.col("i") / (d // m)).cast("int").alias("part"), (F.col("i") % (d // m)).cast("int").alias("dim"), "x")


def sparse(vector: Column) -> Column:
    """Array to map of its non-zero components."""
    kept = F.filter(F.transform(vector, lambda x, i: F.struct(i.alias("key"), x.alias("value"))), lambda s: s["value"] != 0)
    return F.map_from_entries(kept)


def dense(entries: Column, d: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.try_element_at(entries, i), F.lit(0).cast("long")))
