"""Ranks without gathering rows in one task, and top-k per group.

Rows are dealt to ranges by *literal* bounds, collected once. Range membership is then a
function of the value alone, so the count of a range and the rows ranked in it agree in
every plan, however it is partitioned, coalesced or run again.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

ROWS_PER_RANGE = 2_000_000
FAN_OUT = 64  # literal bounds of one look-up; more ranges take a second look-up inside the first


def range_bounds(frame: DataFrame, order: str, parts: int) -> list:
    """At most parts - 1 increasing values that cut the rows into ranges of about one size."""
    if parts < 2:
        return []
    shares = [i / parts for i in range(1, parts)]
    found = frame.agg(F.percentile_approx(order, shares, 20 * parts).alias("b")).first()["b"]
    return sorted({b for b in found or [] if b is not None})


def _tree(x: Column, bounds: list, first: int = 0) -> Column:
    """Number of bounds not above x, by a balanced tree of comparisons."""
    if not bounds:
        return F.lit(first)
    half = len(bounds) // 2
    return F.when(x >= F.lit(bounds[half]), _tree(x, bounds[half + 1 :], first + half + 1)).otherwise(_tree(x, bounds[:half], first))


def range_of(x: Column, bounds: list) -> Column:
    """The range (0 .. len(bounds)) of a value; nulls are in the first."""
    if len(bounds) < FAN_OUT:
        return _tree(x, bounds)
    step = -(-len(bounds) // FAN_OUT)
    outer = bounds[step - 1 :: step]  # each closes a run of ``step`` bounds
    inner = F.array(*[F.array(*[F.lit(b) for b in bounds[i * step : (i + 1) * step]]) for i in range(-(-len(bounds) // step))] + [F.array().cast(f"array<{_kind(bounds[0])}>")])
    at = _tree(x, outer)
    return at * step + F.size(F.filter(F.get(inner, at), lambda b: b <= x))


def _kind(value) -> str:
    return "double" if isinstance(value, float) else "bigint"


def parts_for(frame: DataFrame, rows: int) -> int:
    """Ranges for so many rows: the shuffle partitions, more where those would grow too large."""
    return max(int(frame.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-rows // ROWS_PER_RANGE))


def ranked(frame: DataFrame, order: str, name: str, by: tuple[str, ...] = (), total: str | None = None, ties: tuple[str, ...] = ()) -> DataFrame:
    """Rank from 0 by a column (``ties`` orders its equal values) within each group of ``by`` (all
    rows without it), and on request the size of the group. A group's rows are ranked range by
    range, so a hot group is sorted by many tasks; what lies before a range comes from counts."""
    bounds = range_bounds(frame, order, parts_for(frame, frame.count()))
    placed = frame.withColumn("_p", range_of(F.col(order), bounds))
    keys = [*by, "_p"]
    counts = placed.groupBy(*keys).agg(F.count("*").alias("_n"))
    group = W.partitionBy(*by) if by else W.partitionBy(F.lit(0))  # a row for each range, not for each row
    before = group.orderBy("_p").rowsBetween(W.unboundedPreceding, -1)
    offsets = counts.select(*keys, F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_first"), F.sum("_n").over(group).alias("_total"))
    local = placed.withColumn("_r", F.row_number().over(W.partitionBy(*keys).orderBy(order, *ties)) - 1)
    same = F.lit(True)
    for k in keys:  # null groups and nulls of the order column keep their rows
        same = same & F.col(f"l.{k}").eqNullSafe(F.col(f"o.{k}"))
    side = offsets if by else F.broadcast(offsets)
    joined = local.alias("l").join(side.alias("o"), same)
    kept = [F.col(f"l.{c}") for c in frame.columns]
    return joined.select(*kept, (F.col("_first") + F.col("_r")).cast("long").alias(name), *([F.col("_total").alias(total)] if total else []))


def global_rank(frame: DataFrame, order: str, name: str = "rank", ties: tuple[str, ...] = ()) -> DataFrame:
    """Rank from 0 in the order of a column."""
    return ranked(frame, order, name, ties=ties)


def prefix_ends(frame: DataFrame, order: str, limit: Column, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, _end): the value of a unique column that closes the first ``limit`` rows of each group
    (of all rows without ``by``); ``limit`` may use the group's size ``_total``. Only the range
    that holds a group's end is sorted."""
    bounds = range_bounds(frame, order, parts_for(frame, frame.count()))
    placed = frame.select(*by, order, range_of(F.col(order), bounds).alias("_p"))
    counts = placed.groupBy(*by, "_p").agg(F.count("*").alias("_n"))
    group = W.partitionBy(*by) if by else W.partitionBy(F.lit(0))
    before = F.coalesce(F.sum("_n").over(group.orderBy("_p").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    sized = counts.select(*by, "_p", "_n", before.alias("_first"), F.sum("_n").over(group).alias("_total")).withColumn("_need", F.least(limit, F.col("_total")))
    ends = sized.where((F.col("_first") < F.col("_need")) & (F.col("_need") <= F.col("_first") + F.col("_n"))).select(*by, "_p", (F.col("_need") - F.col("_first")).alias("_at"))
    local = placed.join(ends, [*by, "_p"]).withColumn("_r", F.row_number().over(W.partitionBy(*by, "_p").orderBy(order)))
    return local.where("_r = _at").select(*by, F.col(order).alias("_end"))


def value_of_rank(frame: DataFrame, order: str, wanted: list[int], rows: int | None = None) -> list:
    """Values of a unique column at the given ranks (from 0); only the ranges that hold them are sorted."""
    rows = frame.count() if rows is None else rows
    bounds = range_bounds(frame, order, parts_for(frame, rows))
    placed = frame.select(order, range_of(F.col(order), bounds).alias("_p"))
    sizes = {r["_p"]: r["n"] for r in placed.groupBy("_p").agg(F.count("*").alias("n")).collect()}
    first, at = {}, 0
    for p in sorted(sizes):
        first[p], at = at, at + sizes[p]
    local: dict[int, list[int]] = {}
    for rank in sorted(set(wanted)):
        p = max(p for p in first if first[p] <= rank)
        local.setdefault(p, []).append(rank - first[p])
    rank = F.row_number().over(W.partitionBy("_p").orderBy(order)) - 1
    own = placed.where(F.col("_p").isin(list(local))).withColumn("_r", rank)
    pairs = frame.sparkSession.createDataFrame([(p, r) for p, rs in local.items() for r in rs], "_p int, _r int")
    found = {(r["_p"], r["_r"]): r[order] for r in own.join(F.broadcast(pairs), ["_p", "_r"]).collect()}
    by_rank = {first[p] + r: v for (p, r), v in found.items()}
    return [by_rank[rank] for rank in wanted]


def scalar_neighbours(values: DataFrame, queries: DataFrame) -> DataFrame:
    """(x) and (qid, v) -> (qid, v, below, above): the nearest value on either side (itself if equal, null
    if none). Values and queries are sorted together range by range; a range knows the nearest
    values of the ranges beside it from a row for each range."""
    values = values.distinct()
    bounds = range_bounds(values, "x", parts_for(values, values.count()))
    both = values.select(F.lit(None).cast("long").alias("qid"), F.col("x").alias("v"), F.col("x")).unionByName(queries.select("qid", "v", F.lit(None).cast("long").alias("x")))
    placed = both.withColumn("_p", range_of(F.col("v"), bounds))
    ends = placed.groupBy("_p").agg(F.min("x").alias("_low"), F.max("x").alias("_high"))
    order = W.partitionBy(F.lit(0)).orderBy("_p")  # a row for each range
    carried = ends.select("_p", F.max("_high").over(order.rowsBetween(W.unboundedPreceding, -1)).alias("_before"), F.min("_low").over(order.rowsBetween(1, W.unboundedFollowing)).alias("_after"))
    # Both frames grow from their partition's begin: one that ends there is summed anew for each row.
    up, down = (W.partitionBy("_p").orderBy(o).rangeBetween(W.unboundedPreceding, 0) for o in (F.col("v"), F.col("v").desc()))
    inside = placed.select("qid", "v", "_p", F.max("x").over(up).alias("_b"), F.min("x").over(down).alias("_a")).where("qid is not null")
    return inside.join(F.broadcast(carried), "_p").select("qid", "v", F.coalesce("_b", "_before").alias("below"), F.coalesce("_a", "_after").alias("above"))


def top_k(frame: DataFrame, k: int, by: list[str], order: list[Column | str], name: str = "rk") -> DataFrame:
    """Rows of rank at most k in each group; Spark limits groups before and after the shuffle."""
    w = W.partitionBy(*by).orderBy(*order)
    return frame.withColumn(name, F.row_number().over(w)).where(F.col(name) <= k).withColumn(name, F.col(name).cast("long"))
