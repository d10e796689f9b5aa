"""What both classifiers share: bounded labelled samples and a small logistic fit."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecspark.llm.common import Scratch, arrow_rows, bounded_sample, fold, slices


def labelled_sample(scratch: Scratch, documents: DataFrame, labels: DataFrame, target: str, parts: int, held: int, limit: int) -> DataFrame:
    """At most ``limit`` labelled rows (doc_id, text, label) outside the held-out fold, written once.

    The ids are chosen by a hash, so the sample is alike on any partitioning; joining
    them to the texts broadcasts at most ``limit`` ids.
    """
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(target).cast("int").alias("label"))
    known = known.where("doc_id is not null and label is not null").where(fold("doc_id", parts) != held).groupBy("doc_id").agg(F.max("label").alias("label"))
    chosen = F.broadcast(bounded_sample(known, "doc_id", limit))
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return scratch.keep(texts.join(chosen, "doc_id").select("doc_id", F.coalesce("text", F.lit("")).alias("text"), "label"), f"{target}-sample")


def scored_rows(documents: DataFrame, make: Callable[[], Callable[[list], list[float]]], rows: int = 512) -> DataFrame:
    """Rows with a column ``score`` that ``make()`` gives for their texts."""
    fields = ", ".join(f"{n} {t}" for n, t in documents.dtypes) + ", score double"
    place = documents.columns.index("text")

    def state():
        each = make()

        def run(batch: pa.RecordBatch):
            for part in slices(batch, rows):
                scores = pa.array(each(part.column(place).to_pylist()), pa.float64())
                yield pa.RecordBatch.from_arrays([*part.columns, scores], names=[*part.schema.names, "score"])

        return run

    return arrow_rows(documents, state, fields)


def sigmoid(x):
    return 1.0 / (1.0 + np.exp(-np.clip(x, -40, 40)))


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, steps: int = 50) -> np.ndarray:
    """Newton's method with a ridge; the last weight is the intercept. Columns are scaled within."""
    if not len(y):
        return np.append(np.zeros(x.shape[1]), -3.0)
    scale = np.maximum(np.abs(x).max(axis=0), 1e-9)
    a = np.column_stack([x / scale, np.ones(len(y))])
    w = np.zeros(a.shape[1])
    penalty = ridge * np.append(np.ones(x.shape[1]), 1e-3)
    for _ in range(steps):
        p = sigmoid(a @ w)
        step = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + np.diag(penalty), a.T @ (y - p) - penalty * w)
        w = w + np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-8:
            break
    return np.append(w[:-1] / scale, w[-1])
