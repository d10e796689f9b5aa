"""Codes of many lists are laid out by list."""

import numpy as np
from pyspark.sql import functions as F

from vecspark.operators import packed
from vecspark.operators.codebook import PQModel


def test_a_list_lies_in_few_tasks(spark):
    """Every task held codes of every list, so each made the tables of all queries."""
    rng = np.random.default_rng(3)
    lists = np.where(np.arange(6000) < 4000, 0, rng.integers(1, 12, 6000))  # one of them large
    codes = rng.integers(0, 256, (6000, 8)).astype(np.uint8)
    rows = [(int(i), int(x), bytes(c)) for i, (x, c) in enumerate(zip(lists, codes, strict=True))]
    frame = spark.createDataFrame(rows, "vec_id long, list_id long, code binary").repartition(16)
    laid = packed.by_list(frame).cache()
    held = laid.groupBy(F.spark_partition_id().alias("p"), "list_id").count().collect()
    parts = {r["p"] for r in held}
    assert len(held) <= len(parts) + 12
    assert len({r["p"] for r in held if r["list_id"] == 0}) > 1
    assert sorted(map(tuple, laid.collect())) == rows

    model = PQModel(8, 8, 8, np.sort(rng.integers(0, 4096, (8, 256, 1)), axis=1).astype(np.int64), None)
    queries = spark.createDataFrame([(i, rng.integers(0, 4096, 8).tolist()) for i in range(40)], "qid long, e array<long>").cache()
    probes = spark.createDataFrame([(i, i % 12) for i in range(40)], "qid long, list_id long")
    counts = [sorted(map(tuple, packed.listed_counts(x, queries, probes, model, 1, 1).collect())) for x in (frame, laid)]
    assert counts[0] == counts[1] and len(counts[0]) == 40 and sum(r[3] for r in counts[0]) > 0


def test_the_queries_of_lists_read_that_layout(spark, sf, monkeypatch):
    from vecspark.queries import models
    from vecspark.queries.catalog import QUERIES

    seen, kept = [], packed.by_list
    monkeypatch.setattr(packed, "by_list", lambda codes: seen.append(codes) or kept(codes))
    for name, k in (("w_large_bounded", 64), ("w_list_size", 8)):
        models._KEPT.pop((spark.sparkContext.applicationId, sf, "v1listed", k), None)
        QUERIES[name](spark, sf)
    assert len(seen) == 2
