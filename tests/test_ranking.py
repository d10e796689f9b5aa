"""Ranks on tables larger than a partition: no row may be lost, whatever the shuffle does."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecspark.functions import ranking
from vecspark.operators import encode, scan


@pytest.fixture(params=["4", "200"])
def partitions(spark, request):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", request.param)
    spark.conf.set("spark.sql.adaptive.enabled", "true")
    yield int(request.param)
    spark.conf.set("spark.sql.shuffle.partitions", before)


def wide(spark, n: int):
    """Ids in clumps, rows of 64 longs."""
    ids = spark.range(n).select((F.col("id") * 3 + F.when(F.col("id") > n // 2, 10**12).otherwise(0)).alias("vec_id"))
    return ids.withColumn("e", F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.col("vec_id") + i))


def test_global_rank_keeps_all_rows(spark, partitions):
    n = 500_000 if partitions == 4 else 200_000
    got = ranking.global_rank(wide(spark, n), "vec_id").select("rank", (F.size("e") == 64).alias("whole"), "vec_id").cache()
    row = got.agg(F.count("*"), F.countDistinct("rank"), F.min("rank"), F.max("rank"), F.count_if("whole")).first()
    assert tuple(row) == (n, n, 0, n - 1, n)
    jumps = got.selectExpr("rank = vec_id div 3 or vec_id >= 1000000000000 as right").where("not right").count()
    assert jumps == 0


def test_ranks_with_ties_nulls_and_hot_groups(spark, partitions):
    rows = spark.range(60_000).select(F.when(F.col("id") % 3 == 0, F.lit(7)).otherwise(F.col("id") % 50).alias("g"), F.col("id").alias("vec_id"))
    got = ranking.ranked(rows, "vec_id", "rank", ("g",), "n")
    bad = got.groupBy("g").agg(F.count("*").alias("c"), F.max("rank").alias("m"), F.countDistinct("rank").alias("d"), F.max("n").alias("n")).where("c <> m + 1 or c <> d or c <> n")
    assert bad.isEmpty() and got.count() == 60_000
    tied = spark.createDataFrame([(None, 1), (5, 2), (5, 3), (1, 4)], "k long, vec_id long")
    assert [r["vec_id"] for r in ranking.global_rank(tied, "k", ties=("vec_id",)).orderBy("rank").collect()] == [1, 4, 2, 3]
    assert ranking.global_rank(rows.where("false"), "vec_id").isEmpty()


def test_ranges_agree_with_search_for_many_bounds(spark):
    for n in (0, 1, 5, 63, 64, 65, 200, 500):
        bounds = list(range(10, 10 + 7 * n, 7))
        xs = list(range(0, 20 + 7 * n, 3))
        frame = spark.createDataFrame([(x,) for x in xs], "x long")
        got = {r["x"]: r["p"] for r in frame.select("x", ranking.range_of(F.col("x"), bounds).alias("p")).collect()}
        assert [got[x] for x in xs] == np.searchsorted(bounds, xs, side="right").tolist()


def test_values_and_prefixes(spark, partitions):
    frame = wide(spark, 100_000)
    wanted = [0, 1, 33_333, 99_999]
    ids = sorted(r["vec_id"] for r in frame.select("vec_id").collect())
    assert ranking.value_of_rank(frame, "vec_id", wanted) == [ids[i] for i in wanted]
    placed = scan.with_prefix(frame.select("vec_id"), 0.01, None, 10)
    assert placed.where("prefix").agg(F.count("*"), F.max("vec_id")).first()[:] == (1000, ids[999])
    lists = frame.select("vec_id", (F.col("vec_id") % 5).alias("list_id"))
    marked = scan.with_prefix(lists, None, 20, 7, ("list_id",))
    assert marked.count() == 100_000
    assert {r["n"] for r in marked.where("prefix").groupBy("list_id").agg(F.count("*").alias("n")).collect()} == {20}


def test_blocks_keep_all_codes(spark, partitions):
    codes = spark.range(100_000).select(F.col("id").alias("vec_id"), (F.col("id") % 16).alias("c0"), (F.col("id") % 7).alias("c1"))
    blocks = encode.pack_blocks(codes, 2)
    assert blocks.agg(F.sum(F.size("row")), F.countDistinct("block")).first()[:] == (200_000, 6250)
