"""Best rows by a sum of per-column scores, bounded by bucket maxima before the exact sum."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.functions.vectors import total


def topk_scored(frame: DataFrame, tables: list[list[int]], k: int, best: list[str], ties: list[str], bucket: int = 8) -> DataFrame:
    """Columns k0, k1, .. index the score tables; the k rows of the greatest (score, best), ties ascending.

    The k-th score of a small prefix is a threshold; codes are grouped in buckets whose
    maxima bound the sum, and only rows whose bound reaches the threshold are summed.
    """
    lit = [F.array(*[F.lit(x) for x in t]) for t in tables]
    top = [F.array(*[F.lit(max(t[i : i + bucket])) for i in range(0, len(t), bucket)]) for t in tables]
    code = [F.col(f"k{j}").cast("int") for j in range(len(tables))]
    score = total([t[c] for t, c in zip(lit, code, strict=True)])
    bound = total([t[F.floor(c / bucket).cast("int")] for t, c in zip(top, code, strict=True)])
    order = [F.col("score").desc(), *[F.col(c).desc() for c in best], *ties]
    prefix = frame.limit(1000).withColumn("score", score).orderBy(F.col("score").desc()).limit(k).agg(F.min("score").alias("_thr"), F.count("*").alias("_n"))
    kept = frame.crossJoin(F.broadcast(prefix)).where((bound >= F.col("_thr")) | (F.col("_n") < k))
    return kept.select(*ties, score.cast("long").alias("score"), *best).orderBy(*order).limit(k)
